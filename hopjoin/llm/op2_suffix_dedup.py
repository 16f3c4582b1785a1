"""Removal of repeated 100-byte strings with sharded suffix arrays.

Every window of LENGTH bytes holds an anchor: the leftmost least hash among its GRAM-byte substrings, a choice that depends
on the window's bytes alone.  Windows of one anchor occurrence are consecutive; the bytes under them are a piece.  Equal
windows therefore lie in pieces of equal anchors, at equal distance from it, and pieces can be sharded by anchor.

1. Anchors and piece digests are computed where the text is read; equal pieces within a task are settled there and only the
   first goes on, so a passage that a third of all documents share costs one row per task.
2. Sorted by (anchor, piece, place), all but the first of equal pieces are marked whole; the first of each piece goes on
   only if its anchor has several different pieces - the rims of copies.  Equal pieces are recognised by 128 bits (the
   64-bit anchor and a 64-bit digest of all bytes, length and anchor place).
3. Those pieces' bytes are gathered in shards of whole anchors; each shard's suffix array is built by induced sorting, its
   permuted common prefixes computed, and runs of suffixes that agree in LENGTH bytes give the repeats: all but the first
   place of a run are marked.
4. Marks are united per document and the kept bytes digested.

Frequent anchors (a greeting that a third of all documents begin with, each going on differently) are never one task's work:
those that a hashed sample of the documents shows often are dealt by anchor and piece in step 2, and in step 3 any anchor
with more than HOT different pieces takes its windows one by one through the sorted comparison of step 2, dealt by the
window's bytes.  Which way an anchor goes changes no result.

Defined results: a null text is empty; texts under LENGTH bytes lose nothing; a null doc_id comes before all others; rows
that share an id are one document if their texts are equal (each such row has the same result) and otherwise are documents
of their own, ordered by a 64-bit text hash; ids are integers; input columns named like a result column are replaced by it;
an empty table gives no rows.  Long texts are read whole, in overlapping blocks.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, safe_prefix, table, whole_text
from .suffixes import common_prefixes, suffix_array

LENGTH = 100
GRAM = 24
HOT = 20_000
SHARD_BYTES = 1 << 20
FLUSH = 1 << 21
BLOCK = 1 << 22
_U = np.uint64
_BASE = 0x9E3779B97F4A7C15
#: place = byte offset (any), windows (10 bits)
CNT_BITS = 10
#: one document in SAMPLE is looked at for frequent anchors; those with OFTEN pieces there are dealt by piece, MOST at most
SAMPLE, OFTEN, MOST = 64, 256, 20_000


def _weights() -> np.ndarray:
    t = (np.arange(256, dtype=_U) + _U(1)) * _U(_BASE)
    t ^= t >> _U(31)
    return (t * _U(0xD6E8FEB86659FD93)) | _U(1)


WEIGHTS = _weights()


def gram_hashes(v: np.ndarray) -> np.ndarray:
    """Hash of each GRAM (24) weights, by doubling."""
    def up(h, step, m):
        return h[:-step] * _U(m) + h[step:]

    h8 = up(up(up(v, 1, 0x9FB21C651E98DF25), 2, 0xC2B2AE3D27D4EB4F), 4, 0xA0761D6478BD642F)
    h16 = up(h8, 8, 0xE7037ED1A0B428DB)
    n = len(v) - GRAM + 1
    h = h16[:n] * _U(0x8EBC6AF09C88C6E3) + h8[16 : 16 + n]
    h = (h ^ (h >> _U(31))) * _U(0x7FB5D329728EA185)
    return h ^ (h >> _U(27))


def pieces_of(b: np.ndarray, powers: np.ndarray, inverse: np.ndarray):
    """anchor hash, piece digest, first window, windows - of one text block of at least LENGTH bytes."""
    v = WEIGHTS[b]
    h = gram_hashes(v)
    width = LENGTH - GRAM + 1
    m, w = (h & ~_U((1 << 24) - 1)) | np.arange(len(h), dtype=_U), 1
    while 2 * w <= width:
        m, w = np.minimum(m[:-w], m[w:]), 2 * w
    if width > w:
        m = np.minimum(m[: w - width], m[width - w :])
    at = (m & _U((1 << 24) - 1)).astype(np.int64)
    first = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
    end = np.r_[first[1:], len(at)]
    sums = np.cumsum(np.r_[_U(0), v * powers[: len(v)]])
    digest = (sums[end + LENGTH - 1] - sums[first]) * inverse[first]
    digest ^= digest >> _U(29)
    # the place of the anchor in its piece belongs to the piece's identity, as does the piece's length
    digest = (digest + ((at[first] - first).astype(_U) << _U(12)) + (end - first).astype(_U)) * _U(0xBF58476D1CE4E5B9)
    return h[at[first]], digest, first, end - first


def merged(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Union of half-open intervals; touching ones join."""
    order = np.argsort(start, kind="stable")
    start, end = start[order], np.maximum.accumulate(end[order])
    new = np.r_[True, start[1:] > end[:-1]]
    return start[new], end[np.r_[np.flatnonzero(new)[1:] - 1, len(end) - 1]]


#: kind 0: a piece, 3: a piece of a frequent anchor; 1: a mark, ah and ph being its start and end; 2 and 4: pieces of 0 and 3 that go on.
#: A document is (d, t): its id and, where an id has several texts, the text's hash.
SCHEMA = "kind int, ah bigint, ph bigint, d bigint, t bigint, place bigint"
NAMES = ["kind", "ah", "ph", "d", "t", "place"]


def _rows(kind, *cols: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.broadcast_to(np.int32(kind), len(cols[0])) if np.isscalar(kind) else kind.astype(np.int32)), *[pa.array(c.astype(np.int64, copy=False)) for c in cols]], names=NAMES)


def _settle(a, p, d, t, place):
    """Sorted by piece: flags of the first row of each piece, and of the rows that repeat it at another place."""
    new = np.r_[True, (a[1:] != a[:-1]) | (p[1:] != p[:-1])] if len(a) else np.zeros(0, bool)
    head = np.maximum.accumulate(np.where(new, np.arange(len(a)), 0))
    return new, ~new & ((d != d[head]) | (t != t[head]) | (place != place[head]))


def _marks(d, t, place):
    """Marks of whole pieces, united per document."""
    if not len(d):
        return
    start = place >> CNT_BITS
    end = start + (place & ((1 << CNT_BITS) - 1)) + LENGTH - 1
    order = np.lexsort((start, t, d))
    d, t, start, end = d[order], t[order], start[order], end[order]
    doc = np.cumsum(np.r_[0, (d[1:] != d[:-1]) | (t[1:] != t[:-1])])
    shift = doc << 40
    s, e = merged(start + shift, end + shift)
    k = np.searchsorted(doc, s >> 40)
    yield _rows(1, s - ((s >> 40) << 40), e - ((s >> 40) << 40), d[k], t[k], np.zeros(len(k), np.int64))


def anchor_rows(frequent=None):
    """mapInArrow function over texts (d, t, text) -> pieces that are first in the task and marks of those that are not.

    frequent: a broadcast sorted array of anchors whose pieces get kind 3.
    """

    def run(batches):
        powers, inverse, held, count = np.zeros(0, _U), np.zeros(0, _U), [], 0
        often = frequent.value if frequent is not None else np.zeros(0, np.int64)

        def flush():
            a, p, d, t, place = (np.concatenate(c) for c in zip(*held))
            order = np.lexsort((place, t, d, p, a))
            a, p, d, t, place = a[order], p[order], d[order], t[order], place[order]
            new, again = _settle(a, p, d, t, place)
            yield _rows(np.where(np.isin(a[new], often), 3, 0), a[new], p[new], d[new], t[new], place[new])
            yield from _marks(d[again], t[again], place[again])

        for batch in batches:
            for d, t, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                raw = text.as_buffer()
                b = np.frombuffer(raw, np.uint8) if raw is not None and raw.size else np.zeros(0, np.uint8)
                for at in range(0, max(0, len(b) - LENGTH + 1), BLOCK):
                    part = b[at : at + BLOCK + LENGTH - 1]
                    if len(part) > len(powers):
                        n = max(2 * len(powers), len(part))
                        powers = np.cumprod(np.r_[_U(1), np.full(n - 1, _BASE, _U)])
                        inverse = np.cumprod(np.r_[_U(1), np.full(n - 1, pow(_BASE, -1, 1 << 64), _U)])
                    a, p, first, cnt = pieces_of(part, powers, inverse)
                    held.append((a.view(np.int64), p.view(np.int64), np.full(len(a), d, np.int64), np.full(len(a), t, np.int64), ((first + at) << CNT_BITS) | cnt))
                    count += len(a)
                    if count >= FLUSH:
                        yield from flush()
                        held, count = [], 0
        if held:
            yield from flush()

    return run


def resolve(batches):
    """Rows sorted by (kind, ah, ph, d, t, place): marks of repeated pieces, and the first of each piece that may share windows with others.

    Those are (kind 2) the pieces of an anchor that has several, and (kind 4) all of a frequent anchor.
    """
    last = None  # the first row (ah, ph, d, t, place) of the piece that was read last
    waiting = None  # the only piece so far of the anchor that was read last
    often = None  # the same for pieces of frequent anchors, which come after the others
    for batch in batches:
        cols = [np.asarray(batch.column(i)) for i in range(6)]
        kind = cols[0]
        if (kind == 1).any():
            yield _rows(1, *[c[kind == 1] for c in cols[1:]])
        if (kind == 3).any():
            x = [c[kind == 3] for c in cols[1:]]
            lead = often is not None
            if lead:
                x = [np.r_[np.int64(v), c] for v, c in zip(often, x)]
            new, again = _settle(*x)
            yield from _marks(*[c[again] for c in x[2:]])
            f = np.flatnonzero(new)
            often = tuple(int(c[f[-1]]) for c in x)
            yield _rows(4, *[c[f[lead:]] for c in x])
        a, p, d, t, place = (c[kind == 0] for c in cols[1:])
        if not len(a):
            continue
        lead = last is not None
        if lead:
            a, p, d, t, place = (np.r_[np.int64(x), c] for x, c in zip(last, (a, p, d, t, place)))
        new, again = _settle(a, p, d, t, place)
        yield from _marks(d[again], t[again], place[again])
        f = np.flatnonzero(new)
        last = tuple(int(c[f[-1]]) for c in (a, p, d, t, place))
        # firsts per anchor; the carried row leads the list but was announced before unless it waits
        fa = a[f]
        group = np.cumsum(np.r_[0, fa[1:] != fa[:-1]])
        size = np.bincount(group)
        several = size[group] > 1
        if lead and waiting is None:  # its anchor is known to have several
            several[group == 0] = True
            several[0] = False
        give = f[several]
        if len(give):
            yield _rows(2, a[give], p[give], d[give], t[give], place[give])
        alone = size[-1] == 1 and not several[-1] and not (lead and waiting is None and group[-1] == 0)
        waiting = last if alone else None


def shard_marks(batches):
    """Pieces (ah, d, t, place, bytes) sorted by ah: suffix array of each block of whole anchors, marks of repeats (single windows, united)."""

    def work(held):
        d, t, place = (np.array([h[i] for h in held], np.int64) for i in (1, 2, 3))
        texts = [h[4] for h in held]
        size = np.array([len(x) for x in texts], np.int64)
        begin = np.r_[0, np.cumsum(size + 1)]
        b = np.frombuffer(b"\xff".join(texts) + b"\xff", np.uint8)
        sa = suffix_array(b)
        same = common_prefixes(b, sa) >= LENGTH
        owner = np.searchsorted(begin, sa, "right") - 1
        within = sa - begin[owner]
        valid = within + LENGTH <= size[owner]
        same &= valid & np.r_[False, valid[:-1]]
        run = np.cumsum(~same)
        keep = np.flatnonzero(same | np.r_[same[1:], False])
        if not len(keep):
            return
        o = owner[keep]
        r, dd, tt, spot = run[keep], d[o], t[o], (((place[o] >> CNT_BITS) + within[keep]) << CNT_BITS) | 1
        order = np.lexsort((spot, tt, dd, r))
        r, dd, tt, spot = r[order], dd[order], tt[order], spot[order]
        _, again = _settle(r, np.zeros(len(r), np.int64), dd, tt, spot)
        yield from _marks(dd[again], tt[again], spot[again])

    held, total = [], 0
    for batch in batches:
        for row in zip(*[batch.column(i).to_pylist() for i in range(5)]):
            if total >= SHARD_BYTES and held[-1][0] != row[0]:
                yield from work(held)
                held, total = [], 0
            held.append(row)
            total += len(row[4]) + 1
    if held:
        yield from work(held)


def _apply(batches):
    """(…, text bytes, starts, ends) -> n_bytes, n_removed, n_spans, kept_sha256."""
    for b in batches:
        out = []
        n = b.num_columns
        for raw, s, e in zip(b.column(n - 3), b.column(n - 2).to_pylist(), b.column(n - 1).to_pylist()):
            buf = memoryview(raw.as_buffer() or b"")
            digest, at, gone, spans = hashlib.sha256(), 0, 0, 0
            if s:
                starts, ends = merged(np.array(s, np.int64), np.array(e, np.int64))
                spans, gone = len(starts), int((ends - starts).sum())
                for x, y in zip(starts.tolist(), ends.tolist()):
                    digest.update(buf[at:x])
                    at = y
            digest.update(buf[at:])
            out.append((len(buf), gone, spans, digest.hexdigest()))
        new = [pa.array([x[i] for x in out], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.string()))]
        yield pa.RecordBatch.from_arrays([*b.columns[: n - 3], *new], names=[*b.schema.names[: n - 3], "n_bytes", "n_removed", "n_spans", "kept_sha256"])


def _document_keys(docs: DataFrame, text: str, doc_id: str):
    """Columns (d, t) that tell the documents apart: t is 0 unless some id has several texts."""
    d = F.coalesce(F.col(doc_id).cast("long"), F.lit(-(1 << 63)))
    t = F.xxhash64(whole_text(text))
    shared = docs.select(d.alias("d"), t.alias("t")).groupBy("d").agg(F.min("t").alias("x"), F.max("t").alias("y")).where("x <> y")
    return d, t if shared.limit(1).count() else F.lit(0).cast("long")


def frequent_anchors(texts: DataFrame) -> np.ndarray:
    """Anchors (sorted, at most MOST) that have at least OFTEN different pieces in a task's share of one document in SAMPLE.

    Only the work's distribution depends on them."""
    picked = texts.where(F.pmod(F.xxhash64(F.lit(64), "d", "t", F.octet_length("x")), F.lit(SAMPLE)) == 0)
    counts = picked.mapInArrow(anchor_rows(), SCHEMA).where("kind = 0").groupBy("ah").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= OFTEN)
    found = counts.orderBy(F.desc("n"), "ah").limit(MOST).collect()
    return np.array(sorted(r.ah for r in found), np.int64)


def repeated_spans(texts: DataFrame) -> DataFrame:
    """texts(d, t, x bytes) -> marks (d, t, s, e): byte ranges to remove, not yet united, of the documents (d, t)."""
    spark = texts.sparkSession
    long_enough = texts.where(F.octet_length("x") >= LENGTH)
    order = [*NAMES[:3], "d", "t", "place"]
    rows = long_enough.mapInArrow(anchor_rows(spark.sparkContext.broadcast(frequent_anchors(long_enough))), SCHEMA)
    dealt = F.when(F.col("kind") == 0, F.col("ah")).when(F.col("kind") == 1, F.xxhash64("d", "t")).otherwise(F.xxhash64("ah", "ph"))
    first = materialize(rows.repartition(dealt).sortWithinPartitions(*order).mapInArrow(resolve, SCHEMA))
    marks = first.where("kind = 1")
    asked = first.where("kind in (2, 4)").select("ah", "d", "t", "place").distinct()
    hot = asked.groupBy("ah").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > HOT).select("ah", F.lit(True).alias("hot"))
    asked = asked.join(hot, "ah", "left").select("ah", "d", "t", "place", F.coalesce("hot", F.lit(False)).alias("hot"))
    wanted = asked.groupBy("d", "t").agg(F.collect_list(F.struct("ah", "place", "hot")).alias("w"))
    found = long_enough.join(wanted, ["d", "t"]).select("d", "t", "x", F.explode("w").alias("w"))
    off, cnt = F.shiftright("w.place", CNT_BITS), F.col("w.place").bitwiseAND(F.lit((1 << CNT_BITS) - 1))
    pieces = materialize(found.select(F.col("w.ah").alias("ah"), "d", "t", F.col("w.place").alias("place"), F.substring(F.col("x"), (off + 1).cast("int"), (cnt + LENGTH - 1).cast("int")).alias("x"), F.col("w.hot").alias("hot")))
    sharded = pieces.where("not hot").distinct().repartition("ah").sortWithinPartitions("ah", "d", "t", "place").select("ah", "d", "t", "place", "x").mapInArrow(shard_marks, SCHEMA)
    window = pieces.where("hot").select("d", "t", "place", F.posexplode(F.transform(F.sequence(F.lit(1), F.length("x") - LENGTH + 1), lambda i: F.substring(F.col("x"), i, F.lit(LENGTH)))).alias("i", "y"))
    single = F.shiftleft(F.shiftright("place", CNT_BITS) + F.col("i"), CNT_BITS).bitwiseOR(F.lit(1).cast("long"))
    windows = window.select(F.lit(0).alias("kind"), F.xxhash64("y").alias("ah"), F.xxhash64(F.lit(77), "y").alias("ph"), "d", "t", single.alias("place"))
    hot_marks = windows.repartition("ah").sortWithinPartitions(*order).mapInArrow(resolve, SCHEMA).where("kind = 1")
    return marks.unionByName(sharded).unionByName(hot_marks).select("d", "t", F.col("ah").alias("s"), F.col("ph").alias("e"))


RESULT = {"n_bytes": "bigint", "n_removed": "bigint", "n_spans": "bigint", "kept_sha256": "string"}


def deduplicate(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """docs' columns but the text, with n_bytes, n_removed, n_spans and kept_sha256 per row."""
    p = safe_prefix(docs, "sd")
    d, t = _document_keys(docs, text, doc_id)
    x = whole_text(text).cast("binary")
    marks = materialize(repeated_spans(docs.select(d.alias("d"), t.alias("t"), x.alias("x"))))
    spans = marks.groupBy(F.col("d").alias(f"{p}d"), F.col("t").alias(f"{p}t")).agg(F.collect_list("s").alias(f"{p}s"), F.collect_list("e").alias(f"{p}e"))
    keep = [c for c in docs.columns if c != text and c not in RESULT]
    rows = docs.select(*keep, d.alias(f"{p}d"), t.alias(f"{p}t"), x.alias(f"{p}x"))
    joined = rows.join(spans, [f"{p}d", f"{p}t"], "left").select(*keep, f"{p}x", f"{p}s", f"{p}e")
    schema = ", ".join([*[f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*keep).schema], *[f"{c} {k}" for c, k in RESULT.items()]])
    return joined.mapInArrow(_apply, schema)


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicate(table(spark, sf_dir, "documents").select("doc_id", "text"))
