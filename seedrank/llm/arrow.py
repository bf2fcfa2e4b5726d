"""Arrow helpers for the operators that run Python on the executors."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa


def list_parts(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, values) of a list column, without copies; a null list is an empty one."""
    if column.null_count:
        column = column.fill_null([])
    offsets = column.offsets.to_numpy()
    values = column.values.to_numpy(zero_copy_only=False)
    return offsets, values


def batches_of(column_names: list[str], fn: Callable[..., dict]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A ``mapInArrow`` function that hands the named columns of each batch to ``fn``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_pydict(fn(*[batch.column(batch.schema.get_field_index(c)) for c in column_names]))

    return run


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit integers (multiply and shift rounds)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    x ^= x >> np.uint64(33)
    return x


def window_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of ``k`` neighbours of a 64-bit array."""
    n = len(words) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    words = words.view(np.uint64) if words.dtype != np.uint64 else words
    out = np.full(n, 0x9E3779B97F4A7C15 + k, np.uint64)
    for i in range(k):
        out = mix64(out ^ words[i : i + n]) + np.uint64(i + 1)
    return out


@cache
def byte_bpe(path: str | None = None):
    """The 50k byte-level BPE, one instance a worker process, and the path that holds its ranks.

    The ``.tiktoken`` file states the same vocabulary as ``byte_bpe_50k.json`` without its added
    tokens, and is read several times faster; ``byte_bpe_encoder`` gives the ids of the JSON.
    """
    import base64

    import public_tokenizers
    import tiktoken

    path = path or public_tokenizers.path("byte_bpe_50k.tiktoken")
    with open(path, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    return tiktoken.Encoding("byte_bpe_50k", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


#: A run of white space from which texts go to the reader of the JSON: the fast one exhausts its stack near 1,000,000.
LONG_SPACE = 100_000


@cache
def byte_bpe_encoder(path: str | None = None) -> Callable[[str], list[int]]:
    """Ids as ``byte_bpe_50k.json`` gives them, its added tokens included.

    Texts are split at added tokens and the parts read by ``byte_bpe``; texts with long runs of white
    space go to the reader of the JSON.  With a vocabulary of one's own there are no added tokens.
    """
    import json
    import re

    import public_tokenizers

    fast = byte_bpe(path).encode_ordinary
    if path is not None:
        return fast
    source = public_tokenizers.path("byte_bpe_50k.json")
    with open(source, encoding="utf-8") as f:
        added = {t["content"]: t["id"] for t in json.load(f)["added_tokens"]}
    split = re.compile("(" + "|".join(map(re.escape, sorted(added, key=len, reverse=True))) + ")")
    spaces = re.compile(r"\s{%d}" % LONG_SPACE)

    @cache
    def slow():
        from tokenizers import Tokenizer

        return Tokenizer.from_file(source)

    def encode(text: str) -> list[int]:
        if len(text) >= LONG_SPACE and spaces.search(text):
            return slow().encode(text, add_special_tokens=False).ids
        if not any(t in text for t in added):
            return fast(text)
        return [i for part in split.split(text) if part for i in ([added[part]] if part in added else fast(part))]

    return encode
