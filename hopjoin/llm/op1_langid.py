"""Language identification by error-correcting output codes over character n-grams.

Training rows are hashed to a bounded sample per language (ROWS_PER_LANGUAGE, a parameter; languages with fewer rows keep
all of them) of the LANGUAGES most frequent labels (a parameter; ties to the first in code point order).  Each task adds up hashed n-gram counts per language; the driver receives one count vector of BUCKETS cells
per language, nothing that grows with the documents.  From them every code bit gets a binary n-gram classifier: the
log-ratio of the bucket's frequency in the languages whose codeword has the bit to that in the others.

Codewords are rows of a pseudo-random matrix with greedily widened Hamming distance.  Decoding is loss-weighted: the margin
of each bit is the mean log-ratio over the text's n-grams, a codeword pays the exponential loss of each margin times the
bit's weight for that language (the logistic function of the bit's mean margin on the language's own n-grams, so bits that
the language's text leaves undecided weigh little), and the cheapest codeword wins.  The score is the softmax of the negative losses; `ambiguous` is set when the runner-up is within AMBIGUOUS of it.

Defined results: a null text or one without any letter is `und` with score 0, as is every text when no labelled row
exists; with a single language everything with a letter is that language, score 1; ties go to the first language in code
point order; long texts are read whole, in blocks that count every n-gram once; an empty table gives no rows and, as training
data, no language; other columns play no part in a prediction; an input column named like a result column is replaced by it.
"""

from __future__ import annotations

import unicodedata

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

BUCKETS = 1 << 15
ORDERS = (1, 2, 3)
ROWS_PER_LANGUAGE = 4000
#: labels that are learned: 256 KB of counts each reach the driver
LANGUAGES = 256
AMBIGUOUS = 0.2
BLOCK = 1 << 18
_U = np.uint64

LETTER = np.fromiter((unicodedata.category(chr(c))[0] == "L" for c in range(1 << 16)), bool, 1 << 16)


def normalized(text: str) -> np.ndarray:
    """Lower-case code points with every run of other characters turned into one blank, blank at both ends; empty without a letter."""
    cps = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    letter = LETTER[np.minimum(cps, 0xFFFF)]
    high = cps > 0xFFFF
    if high.any():
        letter = letter.copy()
        letter[high] = [unicodedata.category(chr(c))[0] == "L" for c in cps[high]]
    if not letter.any():
        return np.zeros(0, np.uint32)
    keep = letter.copy()
    keep[1:] |= letter[:-1]
    out = np.where(letter, cps, 32)[keep]
    if out[0] != 32:
        out = np.r_[np.uint32(32), out]
    return out if out[-1] == 32 else np.r_[out, np.uint32(32)]


def buckets_of(cps: np.ndarray, starts: int | None = None) -> np.ndarray:
    """Bucket of every n-gram of the text that begins at one of the first `starts` places, the orders one after the other."""
    c = cps.astype(_U)
    found, h = [], np.zeros(len(c), _U)
    for n in ORDERS:
        if len(c) < n:
            break
        h = h[: len(c) - n + 1] * _U(0x100000001B3) + c[n - 1 :] + _U(n)
        m = h * _U(0x9E3779B97F4A7C15)
        found.append((m[:starts] >> _U(49)).astype(np.int64))
    return np.concatenate(found)


def blocks_of(cps: np.ndarray):
    """Buckets of all n-grams of a text, a block of BLOCK places at a time."""
    for at in range(0, len(cps), BLOCK):
        yield buckets_of(cps[at : at + BLOCK + max(ORDERS) - 1], BLOCK)


def codewords(k: int, seed: int = 5) -> np.ndarray:
    """k codewords of +1/-1 with widely separated rows; every column has both signs."""
    if k < 2:
        return np.ones((k, 1))
    rng = np.random.default_rng(seed)
    length = max(15, 10 * int(np.ceil(np.log2(k))))
    best, best_d = None, -1
    for _ in range(200):
        code = rng.choice([-1.0, 1.0], size=(k, length))
        for j in np.flatnonzero(np.abs(code.sum(0)) == k):
            code[rng.integers(k), j] *= -1
        d = min(int((code[i] != code[j]).sum()) for i in range(k) for j in range(i)) if k <= 64 else 1
        if d > best_d:
            best, best_d = code, d
    return best


class Model:
    """The learned languages, their codewords, the bit classifiers and the decoding weights."""

    def __init__(self, counts: dict[str, np.ndarray]):
        self.langs = sorted(counts)
        self.code = codewords(len(self.langs))
        self.weight = np.ones_like(self.code)
        if len(self.langs) > 1:
            rates = np.stack([counts[x] / max(1.0, counts[x].sum()) for x in self.langs])
            smooth = 0.5 / BUCKETS
            yes = (self.code > 0).astype(float)
            p = (yes.T @ rates) / yes.sum(0)[:, None] + smooth
            q = ((1 - yes).T @ rates) / (1 - yes).sum(0)[:, None] + smooth
            self.bits = np.log(p / q).T.astype(np.float32)  # BUCKETS x bits
            # how sure each bit is of each language on its own n-grams
            sure = rates @ self.bits * self.code
            self.scale = 3.0 / max(1e-9, float(np.median(np.abs(sure))))
            acc = 1 / (1 + np.exp(-np.clip(sure * self.scale, -30, 30)))
            self.weight = acc / np.maximum(acc.sum(1, keepdims=True), 1e-12)

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        cps = normalized(text) if text else np.zeros(0, np.uint32)
        if not len(cps) or not self.langs:
            return "und", 0.0, False
        if len(self.langs) == 1:
            return self.langs[0], 1.0, False
        total, n = np.zeros(self.code.shape[1]), 0
        for b in blocks_of(cps):
            total += (np.bincount(b, minlength=BUCKETS) @ self.bits) if len(b) > 4 * BUCKETS else self.bits[b].sum(0, dtype=np.float64)
            n += len(b)
        margin = total / n * self.scale
        loss = (self.weight * np.exp(-np.clip(margin * self.code, -30, 30))).sum(1)
        odds = np.exp(-(loss - loss.min()) * 4)
        p = odds / odds.sum()
        first = int(np.argmin(loss))
        second = float(np.partition(p, -2)[-2])
        return self.langs[first], float(p[first]), bool(p[first] - second < AMBIGUOUS)


def train(docs: DataFrame, text: str, lang: str, key: str, rows_per_language: int = ROWS_PER_LANGUAGE) -> Model:
    """Fit on rows with a language: a hashed sample of about rows_per_language rows of each."""
    labelled = docs.where(F.col(lang).isNotNull())
    sizes = labelled.groupBy(lang).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), lang).limit(LANGUAGES).collect()
    if not sizes:
        return Model({})
    one = 1 << 20
    share = F.create_map(*[F.lit(v) for r in sizes for v in (r[lang], int(min(1.0, rows_per_language / r.n) * one))])
    picked = labelled.where(F.pmod(F.xxhash64(F.lit(3), F.col(key)), F.lit(one)) < share[F.col(lang)]).select(F.col(lang).alias("l"), F.col(text).alias("t"))

    def run(batches):
        counts: dict[str, np.ndarray] = {}
        for b in batches:
            for l, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                mine = counts.setdefault(l, np.zeros(BUCKETS))
                cps = normalized(t) if t else np.zeros(0, np.uint32)
                for x in blocks_of(cps):
                    mine += np.bincount(x, minlength=BUCKETS)
        for l, c in counts.items():
            nz = np.flatnonzero(c)
            yield pa.RecordBatch.from_arrays([pa.array([l] * len(nz), pa.string()), pa.array(nz.astype(np.int32)), pa.array(c[nz].astype(np.int64))], names=["l", "b", "n"])

    sums = picked.mapInArrow(run, "l string, b int, n bigint").groupBy("l", "b").agg(F.sum("n").alias("n"))
    packed = sums.groupBy("l").agg(F.collect_list(F.struct("b", "n")).alias("x")).select("l", "x.b", "x.n").collect()  # languages x BUCKETS cells
    counts = {r[lang]: np.zeros(BUCKETS) for r in sizes}
    for r in packed:
        counts[r.l][np.array(r.b)] = np.array(r.n)
    return Model(counts)


def identify(docs: DataFrame, model: Model, text: str = "text", names=("lang_pred", "score", "ambiguous")) -> DataFrame:
    """docs with the prediction of every whole text."""
    shipped = docs.sparkSession.sparkContext.broadcast(vars(model))  # plain arrays, BUCKETS x bits floats
    docs = docs.drop(*[n for n in names if n != text])
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema) + f", `{names[0]}` string, `{names[1]}` double, `{names[2]}` boolean"

    def run(batches):
        m = object.__new__(Model)
        m.__dict__ = shipped.value
        for b in batches:
            out = [m.predict(t.as_py()) for t in b.column(text)]
            new = [pa.array([x[0] for x in out], pa.string()), pa.array([x[1] for x in out], pa.float64()), pa.array([x[2] for x in out], pa.bool_())]
            yield pa.RecordBatch.from_arrays([*b.columns, *new], names=[*b.schema.names, *names])

    return docs.mapInArrow(run, schema)


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(False))
    model = train(docs.where(~held), "text", "lang", "doc_id")
    return identify(docs.select("doc_id", "text"), model).select("doc_id", held.alias("held_out"), "lang_pred", "score", "ambiguous")
