"""Language identification with string kernels.

The blended-spectrum presence kernel of two texts is the share of n-grams of characters, of every
length from one to ``MAX_N``, that both have: for each n the number of common distinct n-grams over
the geometric mean of both numbers, averaged over n.  A one-versus-rest kernel ridge regression is
fitted on a bounded sample of labelled texts through Nyström landmarks.  A batch of texts is scored by
matrix products: its presence matrix times that of the landmarks gives the kernels, times the
coefficients the margins.

Defined results: a null text, and one without a letter, is ``und`` with score 0, as is every text
where no label is known; of more than ``MAX_LABELS`` labels those with most texts are learnt; copies of a text
are one training text; ties between labels go to the lesser one; repeated rows are judged one by one; a text of any length is
judged whole, in memory in proportion to its length; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from seedrank.llm.common import map_batches, named, ship, table

MAX_N = 3
#: Bounds of the training sample: labelled texts of each language, those of all languages, and landmarks likewise.
SAMPLE, MAX_TEXTS = 200, 20_000
LANDMARKS, MAX_LANDMARKS = 32, 1024
#: Labels that a model is fitted for at most, and characters of all training texts, about (texts are whole).
MAX_LABELS = 1000
MAX_CHARS = 100_000_000
RIDGE = 1e-3
UNKNOWN = "und"
_LETTER = regex.compile(r"\p{L}")


def spectra(text: str, max_n: int = MAX_N) -> list[np.ndarray]:
    """The distinct n-grams of the lower-cased text, as sorted codes, for n from one to ``max_n``."""
    points = np.frombuffer(text.lower().encode("utf-32-le"), np.uint32).astype(np.uint64)
    out, codes = [], points
    for n in range(1, max_n + 1):
        out.append(np.unique(codes))
        if n < max_n:
            codes = codes[:-1] << np.uint64(21) | points[n:]
    return out


@dataclass
class LanguageModel:
    """``vocabulary[n]``: sorted n-grams of the landmarks; ``landmarks[n]``: a row for each of them, a
    column for each landmark, scaled by the landmark's number of n-grams; ``coefficients``: landmark by language."""

    languages: list[str]
    vocabulary: list[np.ndarray]
    landmarks: list[np.ndarray]
    coefficients: np.ndarray
    sharpness: float

    def kernels(self, texts: list[list[np.ndarray]]) -> np.ndarray:
        """Kernel of each text with each landmark: one matrix product for each n."""
        out = np.zeros((len(texts), self.coefficients.shape[0]), np.float32)
        for n, (known, marks) in enumerate(zip(self.vocabulary, self.landmarks, strict=True)):
            present = np.zeros((len(texts), len(known)), np.float32)
            for row, grams in zip(present, texts, strict=True):
                if len(grams[n]):
                    at = np.searchsorted(known, grams[n])
                    at[at == len(known)] = 0
                    row[at[known[at] == grams[n]]] = 1 / np.sqrt(len(grams[n]))
            out += present @ marks
        return out / len(self.vocabulary)

    def predict(self, texts: list[list[np.ndarray]]) -> tuple[list[str], np.ndarray]:
        margins = self.kernels(texts) @ self.coefficients * self.sharpness
        odds = np.exp(margins - margins.max(axis=1, keepdims=True))
        best = odds.argmax(axis=1)
        return [self.languages[b] for b in best], odds.max(axis=1) / odds.sum(axis=1)


def fit(texts: list[str], labels: list[str], landmarks: int = LANDMARKS, ridge: float = RIDGE, max_n: int = MAX_N, sharpness: float = 4.0) -> LanguageModel:
    """Kernel ridge regression on the given texts; the first ``landmarks`` of each language serve as landmarks."""
    languages, grams = sorted(set(labels)), [spectra(t, max_n) for t in texts]
    landmarks = max(1, min(landmarks, MAX_LANDMARKS // len(languages)))
    chosen, taken = [], dict.fromkeys(languages, 0)
    for i, label in enumerate(labels):
        if taken[label] < landmarks:
            taken[label] += 1
            chosen.append(i)
    vocabulary, matrices = [], []
    for n in range(max_n):
        known = np.unique(np.concatenate([grams[i][n] for i in chosen]))
        marks = np.zeros((len(known), len(chosen)), np.float32)
        for j, i in enumerate(chosen):
            if len(grams[i][n]):
                marks[np.searchsorted(known, grams[i][n]), j] = 1 / np.sqrt(len(grams[i][n]))
        vocabulary.append(known)
        matrices.append(marks)
    model = LanguageModel(languages, vocabulary, matrices, np.zeros((len(chosen), len(languages)), np.float32), sharpness)
    cross = np.concatenate([model.kernels(grams[i : i + 64]) for i in range(0, len(grams), 64)]).astype(np.float64)
    targets = np.where(np.array(labels)[:, None] == np.array(languages)[None, :], 1.0, -1.0)
    among = cross[chosen]
    system = cross.T @ cross + ridge * len(grams) * among + 1e-8 * np.eye(len(chosen))
    model.coefficients = np.linalg.solve(system, cross.T @ targets).astype(np.float32)
    return model


def training_sample(docs: DataFrame, label: str, text: str, per_label: int = SAMPLE, max_chars: int = MAX_CHARS) -> tuple[list[str], list[str]]:
    """At most ``per_label`` unlike texts with a letter of each label, those of least hash.

    A hash threshold that some more texts meet is asked for first; what meets it is cut to the sample
    label by label, before anything leaves the executors.  Long texts are whole, and fewer where they
    would exceed the label's share of ``max_chars`` (one at least).
    """
    rows = docs.select(named(label).alias("label"), named(text).alias("text"))
    rows = rows.where(F.col("label").isNotNull() & F.col("text").rlike("\\p{L}")).withColumn("h", F.xxhash64(F.lit("sample"), "text"))
    # copies of a text count once; the number of unlike ones is needed roughly only
    per_name = rows.groupBy("label").agg(F.approx_count_distinct("h", 0.02).alias("n"), F.count(F.lit(1)).alias("all"))
    counts = {r[0]: r[1] for r in per_name.orderBy(F.col("all").desc(), "label").limit(MAX_LABELS).collect()}
    if not counts:
        return [], []
    per_label = max(1, min(per_label, MAX_TEXTS // len(counts)))
    below = F.lit(False)
    for name, n in counts.items():
        share = min(1.0, 1.2 * (2 * per_label + 20) / n)
        below = below | ((F.col("label") == name) & (F.col("h") <= min(2**63 - 1, int(share * 2**64) - 2**63)))
    unlike = rows.where(below).groupBy("label", "h").agg(F.first("text").alias("text"))
    by_hash = Window.partitionBy("label").orderBy("h")
    sizes = unlike.withColumn("chars", F.length("text").cast("long"))
    sizes = sizes.withColumn("place", F.row_number().over(by_hash)).withColumn("upto", F.sum("chars").over(by_hash))
    found = sizes.where((F.col("place") == 1) | ((F.col("place") <= per_label) & (F.col("upto") <= max_chars // len(counts)))).select("label", "h", "text").collect()
    found.sort(key=lambda r: (r["h"], r["label"]))
    return [r["text"] for r in found], [r["label"] for r in found]


def identify(docs: DataFrame, model: LanguageModel | None, keep: list[str], text: str = "text", batch: int = 64) -> DataFrame:
    """``keep`` columns, lang_pred and score of every text."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for rows in batches:
            texts = rows.column(len(keep)).to_pylist()
            names, scores = [UNKNOWN] * len(texts), np.zeros(len(texts))
            known = [i for i, t in enumerate(texts) if model is not None and t and _LETTER.search(t)]
            for a in range(0, len(known), batch):
                part = known[a : a + batch]
                got, odds = model.predict([spectra(texts[i], len(model.vocabulary)) for i in part])
                for i, name, s in zip(part, got, odds, strict=True):
                    names[i], scores[i] = name, s
            yield pa.RecordBatch.from_arrays([*rows.columns[:-1], pa.array(names, pa.string()), pa.array(scores)], [*keep, "lang_pred", "score"])

    chosen = docs.select(*[named(c) for c in keep], named(text).alias("_scored"))
    schema = StructType(list(chosen.schema)[:-1]).add("lang_pred", "string").add("score", "double")
    return map_batches(chosen, run, schema)


def op2_language(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").withColumn("held_out", F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2)
    texts, labels = training_sample(docs.where(~F.col("held_out")), "lang", "text")
    model = fit(texts, labels) if texts else None
    return identify(docs, model, ["doc_id", "held_out"])
