"""Language-model scores by stupid backoff over n-gram count tables that are partitioned by hash.

Documents are dealt to blocks of about BLOCK_BYTES of text (by a hash of the whole row, so rows without an id spread too).
One order of n-grams after the other, a block lists its distinct n-grams (64-bit hashes) with their counts; the lists are
cut into hash ranges, and the task of a range adds up what all blocks have: its share of the count table.  It answers every
block with the totals of the n-grams the block asked for.  That is the relational join of the exploded n-grams with the
count table, done on packed sorted runs instead of one row per n-gram: a word in every document costs one entry per block,
and counts are 64-bit.  An order's request is dropped when its answers are written, so the disk holds one order at a time.
The answers then meet their blocks, where the documents' n-grams are looked up and the scores summed per document.

A document's own n-grams are taken out of the counts it is scored with, so copies and repeats elsewhere count, its own text
does not.  Score of a word: count(context word) / count(context) where the n-gram occurs elsewhere, else BACKOFF times the
score with the context shortened; an unseen word counts as BACKOFF occurrences.

Defined results: null and wordless texts have n_words 0 and null scores; a corpus of one document backs off everywhere; an
empty table gives no rows; repeated rows are scored like copies; rows equal in every column share a block, as does a text
longer than a block with whatever its hash brings; input columns named like a result column are replaced by it.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, safe_prefix, table, whole_text
from .op9_decontaminate import _arrow_bytes, _mix, word_hashes

ORDER = 3
BACKOFF = 0.4
#: text of a block: small corpora are cut finer, into up to LEAST_BLOCKS blocks of at least a sixteenth of it
BLOCK_BYTES, LEAST_BLOCKS = 16 << 20, 64
_U = np.uint64


def ngrams(words: np.ndarray, counts: np.ndarray, order: int):
    """Per order n: (hash, position) of the n-grams inside one document; position is that of the last word."""
    left = np.arange(len(words)) - np.repeat(np.cumsum(counts) - counts, counts)  # words before it in its document
    h = words.copy()
    for n in range(1, order + 1):
        if n > 1:
            nxt = np.zeros_like(h)
            nxt[1:] = h[:-1] * _U(0x9FB21C651E98DF25) + words[1:]
            h = _mix(nxt)
        at = np.flatnonzero(left >= n - 1)
        yield h[at], at


def pack_counts(c: np.ndarray) -> bytes:
    """Non-negative counts in the least of 1, 2, 4 and 8 bytes that holds them all, the width first."""
    top = int(c.max(initial=0))
    w = next(w for w in (1, 2, 4, 8) if top < 1 << 8 * w)
    return bytes([w]) + c.astype(f"<u{w}").tobytes()


def unpack_counts(b: bytes) -> np.ndarray:
    return np.frombuffer(b, f"<u{b[0]}", offset=1).astype(np.int64)


def pack(h: np.ndarray) -> bytes:
    """Sorted hashes as first value and six-byte gaps (eight where a gap needs more)."""
    gap = np.diff(h)
    wide = len(gap) > 0 and int(gap.max()) >> 48
    raw = gap.view(np.uint8).reshape(-1, 8)[:, : 8 if wide else 6]
    return bytes([8 if wide else 6]) + h[:1].tobytes() + raw.tobytes()


def unpack(b: bytes) -> np.ndarray:
    w = b[0]
    raw = np.frombuffer(b, np.uint8, offset=9).reshape(-1, w)
    gap = np.zeros((len(raw), 8), np.uint8)
    gap[:, :w] = raw
    return np.cumsum(np.r_[np.frombuffer(b[1:9], _U), gap.view(_U).reshape(-1)])


REQUEST = "r int, block int, words bigint, hashes binary, counts binary"
ANSWER = "block int, r int, n int, words bigint, totals binary"


def _requests(ranges: int, n: int):
    """mapInArrow function over (block, text) sorted by block -> the n-grams of each block by range; order 1 also tells its words (r -1)."""

    def emit(block, data, bounds):
        words, counts = word_hashes(data, bounds)
        del data
        *_, (h, _) = ngrams(words, counts, n)
        u, c = np.unique(h, return_counts=True)
        r = ((u >> _U(32)) * _U(ranges) >> _U(32)).astype(np.int64)
        cut = np.flatnonzero(np.r_[True, r[1:] != r[:-1]]) if len(u) else []
        rows = [(int(r[a]), int(block), None, pack(u[a:b]), pack_counts(c[a:b])) for a, b in zip(cut, np.r_[cut[1:], len(u)].astype(int) if len(u) else [])]
        if n == 1:
            rows.append((-1, int(block), len(words), None, None))
        yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in rows], t) for i, t in enumerate((pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.binary()))], names=["r", "block", "words", "hashes", "counts"])

    def run(batches):
        block, held, size = None, [], [0]
        for b in batches:
            ids = np.asarray(b.column(0))
            for at in np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]]) if len(ids) else []:
                end = at + int(np.searchsorted(ids[at:], ids[at], "right"))
                if block is not None and ids[at] != block:
                    yield from emit(block, np.concatenate(held), np.array(size))
                    held, size = [], [0]
                block = ids[at]
                data, bounds = _arrow_bytes(b.column(1).slice(at, end - at))
                held.append(data)
                size += (bounds[1:] + size[-1]).tolist()
        if block is not None:
            yield from emit(block, np.concatenate(held), np.array(size))

    return run


def _totals(n: int):
    """mapInArrow function over requests sorted by (r, block) -> per block and range the totals of its n-grams, in its order."""

    def work(held):
        r = held[0][0]
        if r < 0:
            rows = [(x[1], r, 0, x[2], None) for x in held]
        else:
            lists = [unpack(x[3]) for x in held]
            every, inverse = np.unique(np.concatenate(lists), return_inverse=True)
            total = np.zeros(len(every), np.int64)
            ends = np.cumsum([len(x) for x in lists])
            for x, li, e in zip(held, lists, ends):
                total[inverse[e - len(li) : e]] += unpack_counts(x[4])  # distinct within a list
            rows = [(x[1], r, n, None, pack_counts(total[inverse[e - len(li) : e]])) for x, li, e in zip(held, lists, ends)]
        return pa.RecordBatch.from_arrays([pa.array([x[i] for x in rows], t) for i, t in enumerate((pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.binary()))], names=["block", "r", "n", "words", "totals"])

    def run(batches):
        held = []
        for b in batches:
            for row in zip(*[b.column(i).to_pylist() for i in range(5)]):
                if held and row[0] != held[0][0]:
                    yield work(held)
                    held = []
                held.append(row)
        if held:
            yield work(held)

    return run


def score_words(words, counts, totals, n_corpus: float, order: int) -> np.ndarray:
    """Natural log score of every word; totals[n] are corpus counts of the sorted distinct n-grams of order n."""
    doc = np.repeat(np.arange(len(counts)), counts)
    rest = n_corpus - counts[doc]  # corpus words outside the word's document
    log = None
    context = None  # count elsewhere of the n-1 words before and including each position
    for n, (h, at) in enumerate(ngrams(words, counts, order), 1):
        u, inverse = np.unique(h, return_inverse=True)
        pair, own_of = np.unique(doc[at] * len(u) + inverse, return_inverse=True)
        own = np.bincount(own_of, minlength=len(pair))[own_of]
        c = np.zeros(len(words))
        c[at] = totals[n][inverse].astype(float) - own
        if n == 1:
            log = np.log(np.maximum(c, BACKOFF) / np.maximum(rest, 1.0))
        else:
            has = np.zeros(len(words), bool)
            has[at] = True
            before = np.r_[0.0, context[:-1]]
            seen = has & (c > 0) & (before > 0)
            log = np.where(seen, np.log(np.where(seen, c, 1.0) / np.where(seen, before, 1.0)), np.where(has, log + math.log(BACKOFF), log))
        context = c
    return log


RESULT = {"n_words": "bigint", "log_score": "double", "mean_log_score": "double"}


def lm_scores(docs: DataFrame, text: str = "text", order: int = ORDER, block_bytes: int | None = None) -> DataFrame:
    """docs' columns but the text, with n_words, log_score (sum) and mean_log_score."""
    p = safe_prefix(docs, "lm")
    total = docs.agg(F.coalesce(F.sum(F.octet_length(text)), F.lit(0))).first()[0]
    block_bytes = block_bytes or min(BLOCK_BYTES, max(BLOCK_BYTES // 16, total // LEAST_BLOCKS))
    blocks = int(total // block_bytes) + 1
    keep = [c for c in docs.columns if c != text and c not in RESULT]
    block = F.pmod(F.xxhash64(F.lit(6), *[F.col(f"`{c}`") for c in docs.columns]), F.lit(blocks)).cast("int")
    asked = docs.select(block.alias("block"), whole_text(text).alias("t"))
    answers = None
    for n in range(1, order + 1):
        requests = asked.repartition("block").sortWithinPartitions("block").mapInArrow(_requests(blocks, n), REQUEST)
        one = materialize(requests.repartition("r").sortWithinPartitions("r", "block").mapInArrow(_totals(n), ANSWER))
        answers = one if answers is None else answers.unionByName(one)
    n_corpus = float(answers.where("n = 0").agg(F.sum("words")).first()[0] or 0)
    schema = ", ".join([*[f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*keep).schema], *[f"{c} {k}" for c, k in RESULT.items()]])
    width = len(keep)

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        left = left.combine_chunks()
        texts = left.column(width).combine_chunks() if left.num_rows else pa.array([], pa.string())
        if isinstance(texts, pa.ChunkedArray):
            texts = pa.concat_arrays(texts.chunks)
        words, counts = word_hashes(*_arrow_bytes(texts)) if left.num_rows else (np.zeros(0, _U), np.zeros(0, np.int64))
        rows = sorted(zip(right.column(2).to_pylist(), right.column(1).to_pylist(), right.column(4).to_pylist()), key=lambda x: x[:2])
        none = np.zeros(0, np.int64)
        totals = {n: np.concatenate([none, *[unpack_counts(t) for m, _, t in rows if m == n]]) for n in range(1, order + 1)}
        log = score_words(words, counts, totals, n_corpus, order) if len(words) else np.zeros(0)
        some = counts > 0
        total = np.zeros(len(counts))
        if some.any():
            total[some] = np.add.reduceat(log, (np.cumsum(counts) - counts)[some])
        new = [pa.array(counts), pa.array(total, mask=~some), pa.array(total / np.maximum(counts, 1), mask=~some)]
        return pa.Table.from_arrays([*left.columns[:width], *new], names=[*keep, *RESULT])

    keyed = docs.select(*keep, whole_text(text).alias(f"{p}t"), block.alias(f"{p}b"))
    return keyed.groupBy(f"{p}b").cogroup(answers.where("n > 0").groupBy("block")).applyInArrow(run, schema)


def op6_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = lm_scores(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_words", *[F.round(c, 6).alias(c) for c in ("log_score", "mean_log_score")])


def oracle(docs: str = "documents", order: int = ORDER) -> str:
    """The same rows in DuckDB: every n-gram a row, joined with the count table and with the document's own counts."""
    low = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    grams = " UNION ALL ".join(f"SELECT {n} AS n, rid, i, array_to_string(ws[i - {n - 1}:i], ' ') AS g FROM w WHERE i >= {n}" for n in range(1, order + 1))
    score = f"ln(greatest(max(c) FILTER (WHERE n = 1), {BACKOFF}) / greatest(max(rest), 1))"
    for n in range(2, order + 1):
        c, before = (f"max({x}) FILTER (WHERE n = {n})" for x in ("c", "before"))
        score = f"CASE WHEN {c} > 0 AND {before} > 0 THEN ln({c} / {before}) WHEN {c} IS NOT NULL THEN {score} + ln({BACKOFF}) ELSE {score} END"
    return f"""
    WITH d AS (SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all({low}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM {docs}),
    size AS (SELECT sum(len(ws)) AS n FROM d),
    w AS (SELECT rid, ws, unnest(range(1, len(ws) + 1)) AS i FROM d),
    e AS ({grams}),
    own AS (SELECT n, rid, g, count(*) AS k FROM e GROUP BY n, rid, g),
    every AS (SELECT n, g, sum(k) AS k FROM own GROUP BY n, g),
    c AS (SELECT e.n, e.rid, e.i, (every.k - own.k)::DOUBLE AS c FROM e JOIN own USING (n, rid, g) JOIN every USING (n, g)),
    b AS (SELECT x.*, y.c AS before, (SELECT n FROM size) - len(d.ws) AS rest FROM c x JOIN d USING (rid) LEFT JOIN c y ON y.n = x.n - 1 AND y.rid = x.rid AND y.i = x.i - 1),
    s AS (SELECT rid, i, {score} AS s FROM b GROUP BY rid, i),
    t AS (SELECT rid, sum(s) AS s FROM s GROUP BY rid)
    SELECT doc_id, len(ws)::BIGINT AS n_words, round(s, 6) AS log_score, round(s / len(ws), 6) AS mean_log_score FROM d LEFT JOIN t USING (rid)"""
