"""Candidate generation and pruning for the token-sorted ratio.

`best_pairs` and `pairs_above` are exact at every size: distinct values are cut into blocks of about BLOCK, every block of one
side meets every block of the other (a value set against a dictionary, in blocks), and inside a pair of blocks a character-bag
bound, computed for all pairs at once, decides which few pairs need the longest common subsequence.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hopjoin.functions.strings import qgrams

BLOCK = 2_000
#: characters are told apart by their code modulo this (all of printable ASCII): merged ones only loosen the bound
LETTERS = 96


def length_bound(a: Column, b: Column, t: float) -> Column:
    """LCS is at most the shorter length, so sim > t needs shorter / longer >= t / (2 - t)."""
    la, lb = F.length(a), F.length(b)
    return F.least(la, lb) * (2 - t) >= F.greatest(la, lb) * t - 1e-9


def bag_bound(a: Column, b: Column) -> Column:
    """Upper bound of the ratio: characters in common as bags."""
    letters = lambda c: F.array_remove(F.split(c, ""), "")
    both = F.array_distinct(letters(a))
    count = lambda c, ch: F.length(c) - F.length(F.replace(c, ch, F.lit("")))
    common = F.aggregate(both, F.lit(0), lambda s, ch: s + F.least(count(a, ch), count(b, ch)))
    total = F.length(a) + F.length(b)
    return F.when(total == 0, F.lit(1.0)).otherwise(2.0 * common / F.nullif(total, F.lit(0)))


def levenshtein_bound(a: Column, b: Column, t: float) -> Column:
    """Levenshtein is at most the insert/delete distance, which is at most (1 - t)(|a| + |b|)."""
    return F.levenshtein(a, b) <= F.floor((1 - t) * (F.length(a) + F.length(b)) + 1e-9)


def bounds(a: Column, b: Column, t: float) -> Column:
    """All lossless bounds, cheap before dear."""
    return F.when(~length_bound(a, b, t), False).when(~levenshtein_bound(a, b, t), False).otherwise(True)


def bags(strings: list[str]) -> np.ndarray:
    """Character counts, one row per string."""
    codes = np.frombuffer("".join(strings).encode("utf-32-le", "surrogatepass"), np.uint32) % LETTERS
    owner = np.repeat(np.arange(len(strings)), [len(x) for x in strings])
    return np.bincount(owner * LETTERS + codes, minlength=len(strings) * LETTERS).reshape(-1, LETTERS).astype(np.uint16)


def _lcs_against(x: str):
    """A function y -> longest common subsequence with x."""
    where: dict[str, int] = {}
    for i, ch in enumerate(x):
        where[ch] = where.get(ch, 0) | 1 << i
    full = (1 << len(x)) - 1

    def length(y: str) -> int:
        state = full
        for ch in y:
            u = state & where.get(ch, 0)
            state = ((state + u) | (state - u)) & full
        return len(x) - state.bit_count()

    return length


def tie_key(x: str, y: str) -> str:
    """Order among equally similar pairs: a digest, so that rounds of a one-to-one assignment stay few."""
    return hashlib.md5(f"{x}|{y}".encode()).hexdigest()


def _compare(xv, xs, yv, ys, floor: float | None, what: str):
    """Rows (x, y, sim, tied) of two blocks.

    what="best": per x its largest similarity, the least such y and the y with the least tie key; "above": every pair above
    the floor; "bound": per x the largest bound, nothing else being looked at; "count_best", "count_above": how many
    similarities the first two compute per x.
    """
    order = np.argsort(np.array(yv, object), kind="stable")
    yv, ys = [yv[i] for i in order], [ys[i] for i in order]
    bx, by = bags(xs), bags(ys)
    ly = np.array([len(v) for v in ys], np.int64)
    for i, (v, s) in enumerate(zip(xv, xs)):
        total = ly + len(s)
        bound = np.where(total == 0, 1.0, 2.0 * np.minimum(bx[i], by).sum(1, dtype=np.int64) / np.maximum(total, 1))
        lcs = _lcs_against(s)
        sim = lambda j: 2.0 * lcs(ys[j]) / total[j] if total[j] else 1.0  # noqa: B023, E731
        if what == "bound":
            yield v, None, float(bound.max()), None
            continue
        if what == "count_above":
            yield v, None, float((bound > floor).sum()), None
            continue
        if what == "above":
            for j in np.flatnonzero(bound > floor):
                r = float(sim(j))
                if r > floor:
                    yield v, yv[j], r, None
            continue
        top = float(sim(int(np.argmax(bound))))
        low = top if floor is None else max(top, floor)
        near = np.flatnonzero(bound >= low - 1e-12)
        found: list[int] = []
        made = 1
        for j in near[np.argsort(-bound[near], kind="stable")]:
            if bound[j] < low - 1e-12:
                break
            r, made = float(sim(j)), made + 1
            if r > low:
                low, found = r, [j]
            elif r == low:
                found.append(j)
        if what == "count_best":
            yield v, None, float(made), None
        elif found and (floor is None or low > floor):
            yield v, yv[min(found)], low, min((tie_key(v, yv[j]), yv[j]) for j in found)[1]


def _met(x: DataFrame, y: DataFrame, keys: list[str], floor: float | None, what: str, block: int | None, counts: list[tuple] | None = None) -> DataFrame:
    """Every block of x beside every block of y of its key: both sides are dealt by (key, block, block), so that no key is one task.

    counts: rows (key, values of x, values of y) if they are known, or bounds of them.
    """
    block = block or BLOCK
    kinds = dict(x.dtypes)
    schema = ", ".join([*[f"`{k}` {kinds[k]}" for k in keys], "__nx int, __ny int"])
    if counts is None:
        size = lambda df, out: df.groupBy(*keys).agg(F.count(F.lit(1)).alias(out))
        counts = (size(x, "nx").join(size(y, "ny"), keys) if keys else size(x, "nx").crossJoin(size(y, "ny"))).collect()  # one row per column pair
    rows = [(*c[:-2], -(-c[-2] // block), -(-c[-1] // block)) for c in map(tuple, counts) if c[-2] and c[-1]]
    sizes = x.sparkSession.createDataFrame(rows, schema)
    tasks = max(1, min(sum(r[-2] * r[-1] for r in rows), 20_000))

    def packed(df: DataFrame, mine: str, other: str) -> DataFrame:
        df = df.join(F.broadcast(sizes), keys) if keys else df.crossJoin(F.broadcast(sizes))
        cut = df.withColumn(f"__b{mine}", F.pmod(F.xxhash64("v"), F.col(f"__n{mine}")).cast("int"))
        cut = cut.groupBy(*keys, f"__b{mine}").agg(F.collect_list(F.struct("v", "s")).alias("z"), F.first(f"__n{other}").alias("n"))
        out = cut.select(*keys, f"__b{mine}", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias(f"__b{other}"), F.col("z.v").alias(f"{mine}v"), F.col("z.s").alias(f"{mine}s"))
        return out.repartition(tasks, *keys, "__bx", "__by")

    both = packed(x, "x", "y").join(packed(y, "y", "x"), [*keys, "__bx", "__by"]).select(*keys, "xv", "xs", "yv", "ys")
    n = len(keys)

    def run(batches):
        for b in batches:
            for row in range(b.num_rows):
                key = [b.column(i)[row].as_py() for i in range(n)]
                rows = list(_compare(*[b.column(n + i)[row].as_py() for i in range(4)], floor, what))
                for at in range(0, len(rows), 50_000):
                    part = rows[at : at + 50_000]
                    cols = [pa.array([k] * len(part)) for k in key] + [pa.array([r[i] for r in part], t) for i, t in enumerate((pa.string(), pa.string(), pa.float64(), pa.string()))]
                    yield pa.RecordBatch.from_arrays(cols, names=[*keys, "x", "y", "sim", "tied"])

    schema = ", ".join([*[f"`{k}` {kinds[k]}" for k in keys], "x string, y string, sim double, tied string"])
    return both.mapInArrow(run, schema)


def best_pairs(x: DataFrame, y: DataFrame, keys: list[str] | None = None, floor: float | None = None, block: int | None = None, counts: list[tuple] | None = None) -> DataFrame:
    """x(keys, v, s), y(keys, v, s) of distinct values -> (keys, x, y, sim, tied): each x's best y within its key, exact.

    y is the least of equally good values, tied the one with the least tie key.  With a floor, x without a better y give no
    row; without one, only x whose key has no y at all give none.
    """
    keys = keys or []
    found = _met(x.select(*keys, "v", "s"), y.select(*keys, "v", "s"), keys, floor, "best", block, counts)
    tie = F.md5(F.concat_ws("|", "x", "tied").cast("binary"))
    best = found.groupBy(*keys, "x").agg(F.min(F.struct((-F.col("sim")).alias("m"), F.col("y"))).alias("b"), F.min(F.struct((-F.col("sim")).alias("m"), tie.alias("k"), F.col("tied"))).alias("t"))
    return best.select(*keys, "x", F.col("b.y").alias("y"), (-F.col("b.m")).alias("sim"), F.col("t.tied").alias("tied"))


def pairs_above(x: DataFrame, y: DataFrame, min_score: float, keys: list[str] | None = None, block: int | None = None) -> DataFrame:
    """(keys, x, y, sim) of every pair with sim > min_score, exact."""
    keys = keys or []
    return _met(x.select(*keys, "v", "s"), y.select(*keys, "v", "s"), keys, min_score, "above", block).drop("tied")


def compared(x: DataFrame, y: DataFrame, floor: float | None = None, block: int | None = None) -> DataFrame:
    """One row (compared): how many pairs the exact search for pairs above the floor, or for each x's best, computes."""
    met = _met(x.select("v", "s"), y.select("v", "s"), [], floor, "count_best" if floor is None else "count_above", block)
    return met.agg(F.coalesce(F.sum("sim"), F.lit(0.0)).cast("long").alias("compared"))


def best_bounds(x: DataFrame, y: DataFrame, block: int | None = None) -> DataFrame:
    """(x, bound): per x the largest character-bag bound to any y, without one similarity being computed."""
    met = _met(x.select("v", "s"), y.select("v", "s"), [], None, "bound", block)
    return met.groupBy("x").agg(F.max("sim").alias("bound"))


def band_keys(c: Column, bands: int = 40, rows: int = 2, q: int = 2) -> Column:
    """array<bigint>: one key per band of minimum hashes of the padded q-grams.

    With these defaults a pair whose bigram sets have Jaccard 0.35 shares a band with odds 0.995, at 0.25 with 0.92.
    """
    def of(grams: Column) -> Column:
        def least(seed: int) -> Column:
            return F.array_min(F.transform(grams, lambda g: F.xxhash64(F.lit(seed), g)))

        return F.array(*[F.xxhash64(F.lit(i), *[least(i * rows + r) for r in range(rows)]) for i in range(bands)])

    return F.element_at(F.transform(F.array(qgrams(F.concat(F.lit("^"), c, F.lit("$")), q)), of), 1)


def lsh_pairs(a: DataFrame, b: DataFrame, bands: int = 40, rows: int = 2, q: int = 2, max_block: int = 50_000) -> DataFrame:
    """Pairs that share a band of minimum q-gram hashes (lossy; recall is measured, not assumed).

    Blocks larger than max_block on one side are split by a further hash of the left value and the right side is repeated
    in the splits, so no pair of theirs is lost and no block meets in one task.
    """
    def banded(df: DataFrame, c: str) -> DataFrame:
        return df.withColumn("__k", F.explode(band_keys(F.col(c), bands, rows, q)))

    x, y = banded(a, "sx"), banded(b, "sy")
    big = x.groupBy("__k").agg(F.count(F.lit(1)).alias("n")).select("__k", F.ceil(F.col("n") / max_block).cast("int").alias("__splits"))
    x = x.join(big, "__k").withColumn("__part", F.pmod(F.xxhash64("x"), F.col("__splits")))
    y = y.join(big, "__k").withColumn("__part", F.explode(F.sequence(F.lit(0).cast("long"), F.col("__splits").cast("long") - 1))).drop("__splits")
    return x.drop("__splits").join(y, ["__k", "__part"]).drop("__k", "__part").distinct()
