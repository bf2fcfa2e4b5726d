"""The experiments: how variance and size move with sample size, coordination, weighting and estimator.

Each query is a small table of measures over five sample sizes, averaged over ``RUNS`` replications.  Variances are
conditional ones (given the other keys' ranks), as logarithms to base ten, since they span many orders of
magnitude.  The weights of a workload are read once and kept in flat columns; every design of samples then takes
one pass over them for its thresholds and one for all measures and sizes.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedrank import oracles as O
from seedrank.functions import ranks as R
from seedrank.operators import estimators as E
from seedrank.operators import metrics as M
from seedrank.operators import sketch as S
from seedrank.operators.sweeps import Sweep, flat
from seedrank.plans.workloads import WORKLOADS, long_weights, wide_weights
from seedrank.queries import WORDS, query
from seedrank.sources.store import staged

RUNS = 25
NAMES = {n: list(w.names) for n, w in WORKLOADS.items()}
#: Sample sizes: those of sets with thousands of keys, and of sets of users, of whom a small scale has 150 (29 in an hour).
LARGE, SMALL, TINY = (25, 50, 100, 200, 400), (10, 20, 30, 40, 60), (2, 3, 4, 5, 6)
SHARED, INDEPENDENT = ("ipps", "shared"), ("ipps", "independent")

#: Dispersed sets: workload, numbers of its first assignments that are combined, sample sizes.
DISPERSED = {
    "months": [("part_months", (2, 6, 12), LARGE)],
    "days": [("event_days", (2, 4, 5, 10, 15, 23), SMALL)],
    "high": [("event_high", (2, 5, 10, 15, 23), SMALL)],
    "pair_days": [("event_pair_days", (2, 4), SMALL)],
    "hours": [("event_hours", (2, 4), TINY)],
    "halves": [(f"halves_{x}", (2,), LARGE) for x in ("part_suppliers", "part_gross", "brand_lines", "brand_gross")],
    "years": [("part_years", (2, 7), LARGE)],
    "words": [("words", (2, 4), LARGE)],
}
#: Colocated sets and sample sizes.
COLOCATED = {"pairs": LARGE, "parts": LARGE, "event_day3": SMALL, "event_pair_day3": SMALL, "ohlc": SMALL, "money": LARGE}


class Design:
    """One workload with samples of one design: its sweep, and the same in SQL under table names that begin with ``tag``."""

    def __init__(self, tag: str, workload: str, names: list[str], ks, family: str = "ipps", joint: str = "shared", unit: bool = False):
        self.tag, self.workload, self.names, self.ks, self.family, self.joint, self.unit = tag, workload, names, list(ks), family, joint, unit

    def sweep(self, weights: DataFrame) -> Sweep:
        return Sweep(weights, self.names, self.ks, self.family, self.joint, RUNS, self.unit)

    def tables(self) -> list[str]:
        return O.sweep(self.tag, self.workload, self.names, self.ks, self.family, self.joint, RUNS, self.unit)

    def sums_sql(self, columns) -> str:
        return O.sweep_sums(self.tag, self.names, columns, self.family, self.joint)


def weights_of(spark, sf, workload: str, names: list[str]) -> DataFrame:
    return staged(flat(long_weights(spark, sf, workload), names))


def _log(x) -> "F.Column":
    return F.when(x > 0, F.log10(x))


def _typed(v) -> str:
    return f"CAST('{v}' AS VARCHAR)" if isinstance(v, str) else f"CAST({v} AS INTEGER)"


def _rows(sums: DataFrame, rows: list[tuple[dict, list]]) -> DataFrame:
    """One row for each size and each (labels, [(name, expression over the sums), ...])."""
    cells = [F.struct(*[F.lit(v).alias(n) for n, v in labels.items()], F.col("k").alias("k"), *[x.alias(n) for n, x in values]) for labels, values in rows]
    return sums.select(F.inline(F.array(*cells)))


def _rows_sql(source: str, rows: list[tuple[dict, list]]) -> str:
    one = lambda labels, values: f"SELECT {', '.join([f'{_typed(v)} AS {n}' for n, v in labels.items()] + ['k'] + [f'{x} AS {n}' for n, x in values])} FROM {source}"
    return "\nUNION ALL ".join(one(*r) for r in rows)


def _sql(designs: list[tuple[Design, list]], select: str, more: list[str] = ()) -> str:
    return O.chain(*[t for d, columns in designs for t in [*d.tables(), d.sums_sql(columns)]], *more, select=select)


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _log_sql(x: str) -> str:
    return f"CASE WHEN {x} > 0 THEN log10({x}) END"


def compare(name: str, sets: list[tuple[dict, Design, list, Design, list]], label: list[str]) -> None:
    """Register a table of log10(sum of variances of one design over that of another), for each size.

    A set: labels, then the design and measures above, then those below; both have as many measures as ``label`` rows.
    The two designs are of one workload; equal ones are swept once.
    """

    def plan(spark, sf) -> DataFrame:
        parts, known = [], {}
        for labels, above, up, below, down in sets:
            if (above.workload, *above.names) not in known:
                known[above.workload, *above.names] = weights_of(spark, sf, above.workload, above.names)
            weights = known[above.workload, *above.names]
            n = len(up)
            if below is above:
                both = above.sweep(weights).sums([*up, *down])
                at = lambda j: (F.col(f"v{j}"), F.col(f"v{n + j}"))  # noqa: E731, B023
            else:
                under = below.sweep(weights).sums(down)
                both = above.sweep(weights).sums(up).join(F.broadcast(under.select("k", *[F.col(f"v{j}").alias(f"u{j}") for j in range(n)])), "k")
                at = lambda j: (F.col(f"v{j}"), F.col(f"u{j}"))
            ratio = lambda j: F.round(_log(at(j)[0]) - _log(at(j)[1]), 5)  # noqa: E731, B023
            parts.append(_rows(both, [({**labels, **(own or {})}, [("log_ratio", ratio(j))]) for j, own in enumerate(label[len(parts)])]))
        return _union(parts)

    texts, designs = [], []
    for x, (labels, above, up, below, down) in enumerate(sets):
        n = len(up)
        if below is above:
            designs.append((above, [*up, *down]))
            source, at = f"{above.tag}s", lambda j: (f"v{j}", f"v{n + j}")  # noqa: B023
        else:
            designs += [(above, up), (below, down)]
            source, at = f"{above.tag}s a JOIN {below.tag}s b USING (k)", lambda j: (f"a.v{j}", f"b.v{j}")
        value = lambda j: f"round(({_log_sql(at(j)[0])}) - ({_log_sql(at(j)[1])}), 5)"  # noqa: E731, B023
        texts.append(_rows_sql(source, [({**labels, **(own or {})}, [("log_ratio", value(j))]) for j, own in enumerate(label[x])]))
    query(name, _sql(designs, "\nUNION ALL ".join(texts)))(plan)


def measure(name: str, sets: list[tuple[dict, Design, list, list[dict]]]) -> None:
    """Register a table of log10 of the sum of variances, as it is and over the squared total."""

    def plan(spark, sf) -> DataFrame:
        parts, known = [], {}
        for labels, design, columns, own in sets:
            if design.workload not in known:
                known[design.workload] = weights_of(spark, sf, design.workload, design.names)
            values = lambda j: [("log_sv", F.round(_log(F.col(f"v{j}")), 5)), ("log_nsv", F.round(_log(F.col(f"v{j}")) - 2 * _log(F.col(f"f{j}")), 5))]
            parts.append(_rows(design.sweep(known[design.workload]).sums(columns), [({**labels, **x}, values(j)) for j, x in enumerate(own)]))
        return _union(parts)

    texts = []
    for labels, design, columns, own in sets:
        values = lambda j: [("log_sv", f"round({_log_sql(f'v{j}')}, 5)"), ("log_nsv", f"round(({_log_sql(f'v{j}')}) - 2 * ({_log_sql(f'f{j}')}), 5)")]
        texts.append(_rows_sql(f"{design.tag}s", [({**labels, **x}, values(j)) for j, x in enumerate(own)]))
    query(name, _sql([(d, c) for _, d, c, _ in sets], "\nUNION ALL ".join(texts)))(plan)


for _tag, _sets in DISPERSED.items():
    _w9, _w9l, _w11, _w12, _w12l, _w16, _w16l = [], [], [], [], [], [], []
    for _i, (_w, _ms, _ks) in enumerate(_sets):
        _names = NAMES[_w][: max(_ms)]
        _first = {m: _names[:m] for m in _ms}
        _make = lambda tag, fam="ipps", joint="shared", w=_w, n=_names, ks=_ks, i=_i: Design(f"{tag}{i}", w, n, ks, fam, joint)
        # independent over coordinated, for the minimum: grows with the number of assignments, falls with k
        _low = [("min_l", r) for r in _first.values()]
        _w9.append(({"data": _w}, _make("i", joint="independent"), _low, _make("c"), _low))
        _w9l.append([{"m": m} for m in _first])
        # several assignments against one
        _cols = [(f, m) for m in _first for f in ("min_l", "min_s", "max", "l1_l", "l1_s")]
        for _family in R.FAMILIES:
            _own = [(f"plain_{j}", len(_names)) for j in range(min(len(_names), 7))]
            _w11.append(({"data": _w, "family": _family}, _make("x" if _family == "exp" else "y", _family), [(f, _names[:m]) for f, m in _cols + _own], [{"m": m if f in ("min_l", "min_s", "max", "l1_l", "l1_s") else 1, "measure": f} for f, m in _cols + _own]))
        # the simple against the inclusive selection
        _same = _make("c")
        _w12.append(({"data": _w}, _same, [(f"{f}_s", r) for r in _first.values() for f in ("min", "l1")], _same, [(f"{f}_l", r) for r in _first.values() for f in ("min", "l1")]))
        _w12l.append([{"m": m, "f": f} for m in _first for f in ("min", "l1")])
        # the two rank families side by side
        _fs = [(f, r) for r in _first.values() for f in ("max", "min_l", "l1_l")]
        _w16.append(({"data": _w}, _make("x", "exp"), _fs, _make("y"), _fs))
        _w16l.append([{"m": len(r), "f": f} for f, r in _fs])
    compare(f"q_w9_ind_over_coord_{_tag}", _w9, _w9l)
    measure(f"q_w11_multi_{_tag}", _w11)
    compare(f"q_w12_s_over_l_{_tag}", _w12, _w12l)
    compare(f"q_w16_exp_over_ipps_{_tag}", _w16, _w16l)

# weighted against unweighted coordinated samples, on skewed weights
compare(
    "q_w10_unweighted_over_weighted",
    [({"data": "words"}, Design("u", "words", WORDS, LARGE, unit=True), [("unweighted_max", WORDS), ("unweighted_min", WORDS)], Design("c", "words", WORDS, LARGE), [("max", WORDS), ("min_l", WORDS)])],
    [[{"f": "max"}, {"f": "min"}]],
)


def tradeoff(w: str, ks) -> None:
    """Register variance against storage: single assignments from inclusive and plain estimates, at the size of the samples."""
    names = NAMES[w]
    designs = [(j, Design(f"t{j[0]}", w, names, ks, "ipps", j)) for j in ("shared", "independent")]
    columns = [(f"{kind}_{i}", names) for i in range(len(names)) for kind in ("inclusive", "plain")]
    labels = lambda j: [{"joint": j, "assignment": b, "estimator": kind} for b in names for kind in ("inclusive", "plain")]

    def plan(spark, sf) -> DataFrame:
        weights, parts = weights_of(spark, sf, w, names), []
        for joint, design in designs:
            sweep = design.sweep(weights)
            both = sweep.sums(columns).join(F.broadcast(sweep.sizes()), "k")
            values = lambda i: [("keys", F.round("keys", 3)), ("storage", F.col("k") * len(names)), ("log_nsv", F.round(_log(F.col(f"v{i}")) - 2 * _log(F.col(f"f{i}")), 5))]
            parts.append(_rows(both, [(x, values(i)) for i, x in enumerate(labels(joint))]))
        return _union(parts)

    values = lambda i: [("keys", "round(keys, 3)"), ("storage", f"CAST(k * {len(names)} AS INTEGER)"), ("log_nsv", f"round(({_log_sql(f'v{i}')}) - 2 * ({_log_sql(f'f{i}')}), 5)")]
    texts = [_rows_sql(f"{d.tag}s JOIN {d.tag}z USING (k)", [(x, values(i)) for i, x in enumerate(labels(j))]) for j, d in designs]
    query(f"q_w14_tradeoff_{w}", _sql([(d, columns) for _, d in designs], "\nUNION ALL ".join(texts), [O.sweep_sizes(d.tag, ks) for _, d in designs]))(plan)


def sharing(w: str, ks) -> None:
    """Register the sharing index (distinct keys over k times assignments), and the entries that separate samples keep."""
    names = NAMES[w]
    designs = [(j, Design(f"t{j[0]}", w, names, ks, "ipps", j)) for j in ("shared", "independent")]

    def plan(spark, sf) -> DataFrame:
        weights = weights_of(spark, sf, w, names)
        row = lambda j, d: d.sweep(weights).sizes().select(F.lit(j).alias("joint"), "k", F.round("keys", 3).alias("keys"), (F.col("k") * len(names)).alias("entries"), F.round(F.col("keys") / (F.col("k") * len(names)), 9).alias("sharing_index"))
        return _union([row(j, d) for j, d in designs])

    texts = [f"SELECT CAST('{j}' AS VARCHAR) AS joint, k, round(keys, 3) AS keys, CAST(k * {len(names)} AS INTEGER) AS entries, round(keys / (k * {float(len(names))}), 9) AS sharing_index FROM {d.tag}z" for j, d in designs]
    query(f"q_w15_sharing_{w}", O.chain(*[t for _, d in designs for t in [*d.tables()[:3], O.sweep_sizes(d.tag, ks)]], select="\nUNION ALL ".join(texts)))(plan)


for _w, _ks in COLOCATED.items():
    # inclusive against plain estimates of single assignments, under both rank families
    _sets, _labels = [], []
    for _joint in ("shared", "independent"):
        for _family in R.FAMILIES:
            _d = Design(_joint[0] + _family[0], _w, NAMES[_w], _ks, _family, _joint)
            _sets.append(({"joint": _joint, "family": _family}, _d, [(f"inclusive_{i}", NAMES[_w]) for i in range(len(NAMES[_w]))], _d, [(f"plain_{i}", NAMES[_w]) for i in range(len(NAMES[_w]))]))
            _labels.append([{"assignment": b} for b in NAMES[_w]])
    compare(f"q_w13_inclusive_over_plain_{_w}", _sets, _labels)
    tradeoff(_w, _ks)
    sharing(_w, _ks)

# the generic selection (that of the maximum) against the inclusive one, where whole vectors are known
_d11 = [Design(f"g{i}", w, NAMES[w][:4], ks) for i, (w, ks) in enumerate((("part_months", LARGE), ("event_days", SMALL)))]
compare("q_d11_generic_over_inclusive", [({"data": d.workload}, d, [("max", d.names)], d, [("inclusive_max", d.names)]) for d in _d11], [[None], [None]])

# inclusive estimates of maxima under both coordinated designs of exponential ranks
_IND_KS = (50, 200)


def _inddiff_sql(joint: str, k: int) -> str:
    names = NAMES["part_months"][:4]
    p = O.inclusive("exp", joint, "mx")
    return O.chain(O.ranked("part_months", names, "exp", joint, runs=5), O.bottom_k(k), O.full_cells(names), p.rpartition("adj AS")[0].rstrip(",\n "), select="SELECT log10(avg(sv)) AS v FROM (SELECT run, sum(CASE WHEN mx > 0 THEN mx * mx * (1 / p - 1) ELSE 0 END) AS sv FROM g GROUP BY 1)")


@query("q_d11_inddiff_over_shared", "\nUNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS k, round(a.v - b.v, 5) AS log_ratio FROM ({_inddiff_sql('inddiff', k)}) a, ({_inddiff_sql('shared', k)}) b" for k in _IND_KS))
def _inddiff_over_shared(spark, sf):
    names, parts = NAMES["part_months"][:4], []
    vectors = staged(wide_weights(spark, sf, "part_months", names))
    for k in _IND_KS:
        values = []
        for joint in ("inddiff", "shared"):
            ranked = R.rank_wide(vectors, "exp", joint, runs=5)
            cells = E.full_cells(ranked, S.bottom_k(R.to_long(ranked), k, "exp", joint).meta, names)
            sv = M.conditional_variance(cells, E.f_max, lambda c, j=joint: E.inclusive_p(c, "exp", j))
            values.append(sv.agg(F.log10(F.avg("sv")).alias(joint)))
        parts.append(values[0].crossJoin(F.broadcast(values[1])).select(F.lit(k).alias("k"), F.round(F.col("inddiff") - F.col("shared"), 5).alias("log_ratio")))
    return _union(parts)
