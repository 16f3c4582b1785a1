"""Quality classifier: document evidence combined with host and path posteriors by hierarchical empirical Bayes.

Evidence: a document is the set of its lower-cased word and mark runs, word beginnings and a few shape tokens.  On a bounded hashed sample
of labelled rows (ROWS labelled documents, a parameter; equal texts once) presence counts per token and label are added up;
tokens whose likelihood-ratio statistic is significant (G2, at least 5 documents, MAX_TOKENS at most) become the features of
a logistic model whose ridge grows with the square of a token's distance from the most significant one: credit goes to the
words that carry a label, little to those that only came along in copies.  Two heads share the machinery: `quality` and `toxic`.

Sites: a document's host is its source, its path the pair of source and language.  Per head the documents' probabilities
are averaged per host and per path with grouped aggregation; each mean is shrunk towards its parent (path to host, host to
all) by a beta prior whose strength is estimated from the spread of the means (method of moments), so sparse sites sit at
their parent.  The final log-odds are the document's plus the path's shift from the global rate.  All documents count in
the site statistics - one grouped sum over paths for both heads, from which the hosts follow -; only the token table is
learned on the sample.  The posteriors, one row per path, go back to the documents by broadcast up to SITES paths, by a join
beyond.

Defined results: without labels every document has probability 1/2 for quality and 0 for toxicity and is kept; a null or
empty text has no evidence and gets its site's rate; a null source or language is a site of its own; a text labelled more
than once (by several label rows, or in several documents) is learned from once, with the larger label of each head; label
rows with a null are not learned from; repeated rows give repeated results; an empty table gives no rows; columns named
like a result column are no concern, only the key, text, host and path columns are read.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, table

ROWS = 10_000
MAX_TOKENS = 8_000
G2 = 15.0
RIDGE = 0.3
#: lengths of the word beginnings that are tokens of their own
PREFIXES = (4, 5, 6, 7)
HEADS = ("quality", "toxic")
#: paths whose posteriors are broadcast (some 150 bytes each)
SITES = 100_000
TOKEN = re.compile(r"[^\W_]+|[^\w\s]+|_+")


def tokens(text: str | None) -> set[str]:
    words = TOKEN.findall((text or "").lower())
    found = set(words)
    heads = {f"^{w[:k]}" for w in found for k in PREFIXES if len(w) >= k}
    n = len(words)
    if n >= 20 and len(found) * 4 < n:
        found.add("<repeats>")
    if n >= 20 and sum(map(len, found)) > 12 * len(found):
        found.add("<long>")
    return found | heads


def logistic(rows: np.ndarray, cols: np.ndarray, y: np.ndarray, width: int, ridge: np.ndarray, rounds: int = 400) -> tuple[np.ndarray, float]:
    """Ridge logistic regression on a binary matrix given by its ones (rows, cols): weights and intercept."""
    w, rate = np.zeros(width), (y.sum() + 0.5) / (len(y) + 1)
    b = float(np.log(rate / (1 - rate)))
    gw, gb = np.full(width, 1.0), 1.0
    for _ in range(rounds):
        z = np.bincount(rows, w[cols], len(y)) + b
        e = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - y
        d = np.bincount(cols, e[rows], width) + ridge * w
        gw += d * d
        w -= d / np.sqrt(gw)
        gb += e.sum() ** 2
        b -= e.sum() / np.sqrt(gb)
    return w, b


def fit(docs: DataFrame, labels: DataFrame, text: str, key: str, rows: int = ROWS) -> tuple[dict, dict, dict]:
    """Token weights {token: (quality, toxic)}, intercepts and base rates per head from about `rows` labelled documents."""
    n = labels.count()
    one = 1 << 20
    share = int(min(1.0, rows / n) * one) if n else 0
    picked = labels.where(F.pmod(F.xxhash64(F.lit(8), key), F.lit(one)) < share).select(F.col(key).alias("k"), *[F.col(h).cast("int").alias(h) for h in HEADS])
    picked = picked.where(" and ".join(f"{h} is not null" for h in HEADS))
    # a bounded set of label rows, by the parameter above: it may be broadcast
    both = docs.select(F.col(key).alias("k"), F.col(text).alias("t")).join(F.broadcast(picked), "k").select("t", *HEADS)
    both = materialize(both.groupBy(F.xxhash64("t").alias("h")).agg(F.first("t").alias("t"), *[F.max(h).alias(h) for h in HEADS]).drop("h"))

    def run(batches):
        counts: Counter = Counter()
        for b in batches:
            for t, q, x in zip(*[b.column(i).to_pylist() for i in range(3)]):
                for w in {*tokens(t), ""}:  # "" counts the documents
                    counts[w, q, x] += 1
        items = list(counts.items())
        for at in range(0, len(items), 50_000):
            part = items[at : at + 50_000]
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k, _ in part], pa.string()), *[pa.array([k[i] for k, _ in part], pa.int32()) for i in (1, 2)], pa.array([v for _, v in part], pa.int64())], names=["w", *HEADS, "n"])

    seen = both.mapInArrow(run, "w string, quality int, toxic int, n bigint")
    cells = seen.groupBy("w").agg(*[F.coalesce(F.sum(F.when(F.col(h) == v, F.col("n"))), F.lit(0)).alias(f"{h}{v}") for h in HEADS for v in (0, 1)])
    cells = materialize(cells)
    total = cells.where("w = ''").first()
    if total is None:
        return {}, {"quality": 0.0, "toxic": -30.0}, {"quality": 0.5, "toxic": 0.0}

    def g2(h: str) -> Column:
        a, b, na, nb = F.col(f"{h}1"), F.col(f"{h}0"), float(total[f"{h}1"]), float(total[f"{h}0"])
        if not na or not nb:
            return F.lit(0.0)
        every = na + nb
        ent = lambda x, row, col: F.when(x > 0, x * F.log(x * every / (row * col))).otherwise(0.0)
        has, not_a, not_b = a + b, F.lit(na) - a, F.lit(nb) - b
        value = 2 * (ent(a, has, F.lit(na)) + ent(b, has, F.lit(nb)) + ent(not_a, every - has, F.lit(na)) + ent(not_b, every - has, F.lit(nb)))
        return F.when(has >= 5, value).otherwise(0.0)

    scored = cells.where("w <> ''").select("w", *[g2(h).alias(h) for h in HEADS]).where(F.greatest(*HEADS) >= G2)
    best = scored.orderBy(F.greatest(*HEADS).desc(), "w").limit(MAX_TOKENS).collect()
    names = {r.w: i for i, r in enumerate(best)}
    shipped = docs.sparkSession.sparkContext.broadcast(names)

    def ones(batches):
        known = shipped.value
        for b in batches:
            lists = [np.array(sorted(known[w] for w in known.keys() & tokens(t.as_py())), np.int32).tobytes() for t in b.column(0)]
            yield pa.RecordBatch.from_arrays([pa.array(lists, pa.binary()), b.column(1), b.column(2)], names=["x", *HEADS])

    sample = both.select("t", *HEADS).mapInArrow(ones, "x binary, quality int, toxic int").collect()  # about `rows` rows of packed numbers
    r = np.repeat(np.arange(len(sample)), [len(s.x) // 4 for s in sample])
    c = np.frombuffer(b"".join(bytes(s.x) for s in sample), np.int32).astype(np.int64)
    weights, base, rate = {}, {}, {}
    for h in HEADS:
        y = np.array([s[h] for s in sample], float)
        strength = np.array([max(x[h], 1.0) for x in best])
        weights[h], base[h] = logistic(r, c, y, len(names), RIDGE * (strength.max(initial=1.0) / strength) ** 1.5)
        rate[h] = (y.sum() + 0.5) / (len(y) + 1)
    return {w: tuple(float(weights[h][i]) for h in HEADS) for w, i in names.items()}, base, rate


def _logit(p: Column) -> Column:
    safe = F.greatest(F.lit(1e-6), F.least(F.lit(1 - 1e-6), p))
    return F.log(safe / (1 - safe))


def shrink(sites: DataFrame, keys: list[str], up: dict[str, Column]) -> DataFrame:
    """sites(keys, n, sum_<head>) -> keys and up_<head>: each mean shrunk towards up[head] with a moment estimate of the prior's strength."""
    mean = {h: F.col(f"sum_{h}") / F.col("n") for h in HEADS}
    stats = [x for h in HEADS for x in (F.avg(F.pow(mean[h] - up[h], 2)).alias(f"v_{h}"), F.avg(up[h] * (1 - up[h])).alias(f"w_{h}"))]
    found = sites.agg(F.avg(1 / F.col("n")).alias("i"), *stats).first()
    out = []
    for h in HEADS:
        v, w, i = (found[f"v_{h}"] or 0.0), (found[f"w_{h}"] or 0.0), (found.i or 0.0)
        between = max(v - w * i, 0.0)
        strength = min(1e6, max(1.0, w / between - 1)) if between > 1e-12 else 1e6
        out.append(((F.col(f"sum_{h}") + strength * up[h]) / (F.col("n") + strength)).alias(f"up_{h}"))
    return sites.select(*keys, *out)


def classify(docs: DataFrame, labels: DataFrame, text: str = "text", key: str = "doc_id", host: str = "source", path: str = "lang", rows: int = ROWS) -> DataFrame:
    """key, p_quality, p_toxic, host_quality, path_quality, host_toxic, path_toxic, kept - one row per document."""
    weights, intercept, rate = fit(docs, labels, text, key, rows)
    shipped = docs.sparkSession.sparkContext.broadcast(weights)  # at most MAX_TOKENS tokens

    def run(batches):
        known = shipped.value
        names = known.keys()
        for b in batches:
            sums = []
            for t in b.column(3):
                hits = [known[w] for w in names & tokens(t.as_py())]
                sums.append((sum(x[0] for x in hits), sum(x[1] for x in hits)))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), *[pa.array([s[i] for s in sums], pa.float64()) for i in range(2)]], names=["k", "host", "path", "eq", "et"])

    kind = dict(docs.dtypes)[key]
    slim = docs.select(F.col(key).alias("k"), F.coalesce(F.concat(F.lit("s"), F.col(host)), F.lit("n")).alias("host"), F.coalesce(F.concat(F.lit("s"), F.col(path)), F.lit("n")).alias("path"), F.col(text).alias("t"))
    slim = materialize(slim.mapInArrow(run, f"k {kind}, host string, path string, eq double, et double"))
    odds = {"quality": F.lit(intercept["quality"]) + F.col("eq"), "toxic": F.lit(intercept["toxic"]) + F.col("et")}
    sure = {h: 1 / (1 + F.exp(-odds[h])) for h in HEADS}
    paths = materialize(slim.groupBy("host", "path").agg(F.count(F.lit(1)).alias("n"), *[F.sum(sure[h]).alias(f"sum_{h}") for h in HEADS]))
    hosts = paths.groupBy("host").agg(F.sum("n").alias("n"), *[F.sum(f"sum_{h}").alias(f"sum_{h}") for h in HEADS])
    hosts = materialize(shrink(hosts, ["host"], {h: F.lit(rate[h]) for h in HEADS})).withColumnsRenamed({f"up_{h}": f"host_{h}" for h in HEADS})
    both = paths.join(hosts, "host")
    sites = shrink(both, ["host", "path", *[f"host_{h}" for h in HEADS]], {h: F.col(f"host_{h}") for h in HEADS}).withColumnsRenamed({f"up_{h}": f"path_{h}" for h in HEADS})
    sites = materialize(sites)
    out = slim.join(F.broadcast(sites) if paths.count() <= SITES else sites, ["host", "path"])
    for h in HEADS:
        shift = _logit(F.col(f"path_{h}")) - _logit(F.lit(rate[h]))
        out = out.withColumn(f"p_{h}", 1 / (1 + F.exp(-(odds[h] + shift))))
    kept = (F.col("p_quality") >= 0.5) & (F.col("p_toxic") < 0.5)
    return out.select(F.col("k").alias(key), *[f"{a}_{h}" for h in HEADS for a in ("p", "host", "path")], kept.alias("kept"))


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify(table(spark, sf_dir, "documents").select("doc_id", "text", "source", "lang"), table(spark, sf_dir, "labels"))
