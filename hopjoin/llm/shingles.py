"""Near-duplicate groups at a shingle similarity (five words, 0.8): SimHash covering first, banded minima for what it cannot reach.

At similarity 0.8 two SimHash fingerprints of 64 bits differ in 5 to 14 bits, for which covering masks would need thousands
of tables; covering with radius 2 therefore only proposes the closest pairs.  Further pairs come from 16 bands of 4 minimum
hashes (a pair at 0.8 shares a band with odds above 0.999).  A first round cuts a bucket by the fingerprint's first byte and
pairs every document with the least of its part, and those with the bucket's least, which settles most copies.  Sketches,
the SKETCH smallest 32-bit shingle hashes, decide these pairs where texts have fewer shingles than that; of the others they
only refuse those MARGIN (six standard errors) below the bar, and the full sets of distinct shingles decide the rest.  The
second round takes the buckets whose documents are in different groups by then, with the full sets of their documents, and
compares every pair across groups in place, so that no pair of a bucket is left out, however large the bucket: sizes and all
64 minima refuse first (a pair at 0.8 with odds below a millionth), exact common shingles decide, and only links that join
two groups leave the task.  A mixed bucket is one task's work; what it holds are the sets of that bucket.

Defined results: a null or wordless text has no shingle and is a group of all such rows; fewer words than a shingle are one
shingle; equal word sequences are one class and need no comparison; rows without an id get no group; rows that share an id
are in the group of each of their texts; a group's root is its least id; an empty table gives no rows; other columns play
no part.  Texts are hashed whole.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, components, forget, materialize, whole_text, words_of
from .op7_simhash import class_links, majority, shingle_hashes

BANDS, ROWS, SKETCH = 16, 4, 384
MARGIN = 0.12
_U = np.uint64


def _seeds(n: int) -> np.ndarray:
    return np.random.default_rng(11).integers(1, 1 << 63, size=(2, n), dtype=np.int64).astype(_U) | _U(1)


def profiles(docs: DataFrame, doc_id: str, text: str, k: int) -> DataFrame:
    """doc_id, wh (hash of the word sequence), fp, bands, sketch, n (distinct shingles), minima (a byte of each minimum)."""
    hashed = docs.select(F.col(doc_id).alias("d"), word_key(text).alias("wh"), shingle_hashes(whole_text(text), k).alias("h"))

    def run(batches):
        a, c = _seeds(BANDS * ROWS)
        for b in (x.slice(at, 1000) for x in batches for at in range(0, x.num_rows, 1000)):
            lists = b.column(2)
            offsets = np.asarray(lists.offsets, dtype=np.int64)
            values = (np.asarray(lists.values)[offsets[0] : offsets[-1]] if len(lists.values) else np.zeros(0, np.int64)).view(_U)
            fp = majority(values, offsets)
            bands, sketches, sizes, minima = [], [], [], []
            for i in range(b.num_rows):
                s = np.unique(values[offsets[i] - offsets[0] : offsets[i + 1] - offsets[0]])
                low = np.full(BANDS * ROWS, ~_U(0))
                for at in range(0, len(s), 4096):
                    x = s[at : at + 4096, None] * a + c
                    low = np.minimum(low, (x ^ (x >> _U(29))).min(axis=0))
                key = np.arange(BANDS, dtype=_U)
                for r in range(ROWS):
                    key = (key ^ low[r::ROWS]) * _U(0x9E3779B97F4A7C15)
                    key ^= key >> _U(32)
                minima.append((low * _U(0x9E3779B97F4A7C15) >> _U(56)).astype(np.uint8).tobytes())
                bands.append(key.view(np.int64).tolist() if len(s) else [])
                short = np.unique((s * _U(0xD6E8FEB86659FD93) >> _U(32)).astype(np.uint32))
                sketches.append(short[:SKETCH].tobytes())
                sizes.append(len(short))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(fp.view(np.int64)), pa.array(bands, pa.list_(pa.int64())), pa.array(sketches, pa.binary()), pa.array(sizes, pa.int32()), pa.array(minima, pa.binary())], names=["d", "wh", "fp", "bands", "sketch", "n", "minima"])

    return hashed.mapInArrow(run, f"d {dict(docs.dtypes)[doc_id]}, wh string, fp bigint, bands array<bigint>, sketch binary, n int, minima binary")


def least_equal(similarity: float, odds: float = 1e-6) -> int:
    """The most equal minima that a pair at the similarity has with odds of at least 1 - odds."""
    n, k, below = BANDS * ROWS, 0, 0.0
    while k < n and (below := below + math.comb(n, k) * similarity**k * (1 - similarity) ** (n - k)) < odds:
        k += 1
    return k


def cross_links(similarity: float):
    """Rows (band, key, rep, label, n, minima, s) sorted by band and key -> links (a, b) at the bar between groups of a bucket.

    Each document outside the bucket's largest group meets the whole bucket at once: its shingles' posting lists, added up,
    are the exact common shingles with every other member.  Only links that join two groups leave, so a bucket of m documents
    gives fewer than m rows, however many of its pairs are at the bar.
    """
    need = least_equal(similarity)

    def bucket(label, n, minima, sets):
        group, of, size = np.unique(label, return_inverse=True, return_counts=True)
        ids = np.concatenate(sets)
        owner = np.repeat(np.arange(len(sets)), n)
        order = np.argsort(ids, kind="stable")
        ids, owner = ids[order], owner[order]
        comp, largest = np.arange(len(group)), int(np.argmax(size))
        for i in np.lexsort((of, size[of])):
            if of[i] == largest:
                continue  # it meets the others, never itself
            mine = comp[of]
            other = np.flatnonzero(mine != mine[i])
            other = other[np.minimum(n[other], n[i]) >= similarity * np.maximum(n[other], n[i]) - 1e-9]
            other = other[(minima[other] == minima[i]).sum(axis=1) >= need]
            if not len(other):
                continue
            lo, hi = np.searchsorted(ids, sets[i], "left"), np.searchsorted(ids, sets[i], "right")
            m = hi - lo
            at = np.repeat(lo - np.r_[0, np.cumsum(m)[:-1]], m) + np.arange(m.sum())
            common = np.bincount(owner[at], minlength=len(sets))
            near = other[common[other] >= similarity * (n[other] + n[i] - common[other]) - 1e-9]
            for j in near[np.unique(mine[near], return_index=True)[1]]:  # one link a group is enough
                yield i, j
                comp[comp == comp[of[j]]] = comp[of[i]]

    def work(t):
        t = t.combine_chunks()
        reps = t.column("rep").combine_chunks()
        reps = pa.concat_arrays(reps.chunks) if isinstance(reps, pa.ChunkedArray) else reps
        band, key, label, n = (t.column(c).to_numpy() for c in ("band", "key", "label", "n"))
        minima = np.frombuffer(b"".join(t.column("minima").to_pylist()), np.uint8).reshape(-1, BANDS * ROWS)
        lists = t.column("s").combine_chunks()
        lists = pa.concat_arrays(lists.chunks) if isinstance(lists, pa.ChunkedArray) else lists
        offsets, values = np.asarray(lists.offsets, dtype=np.int64), np.asarray(lists.values)
        sets = [np.sort(values[x:y]) for x, y in zip(offsets[:-1], offsets[1:])]
        n = np.array([len(x) for x in sets], np.int64)
        new = np.flatnonzero(np.r_[True, (band[1:] != band[:-1]) | (key[1:] != key[:-1])])
        for s, e in zip(new, np.r_[new[1:], len(n)]):
            found = [(s + i, s + j) for i, j in bucket(label[s:e], n[s:e], minima[s:e], sets[s:e])]
            if found:
                yield pa.RecordBatch.from_arrays([reps.take(pa.array([x[k] for x in found], pa.int64())) for k in (0, 1)], names=["a", "b"])

    def run(batches):
        held, last = [], None  # rows of the last, unfinished bucket
        for x in batches:
            if not x.num_rows:
                continue
            band, key = x.column(0).to_numpy(), x.column(1).to_numpy()
            if last is not None and (band[0], key[0]) != last:
                yield from work(pa.Table.from_batches(held))
                held = []
            last = (band[-1], key[-1])
            tail = int(np.flatnonzero((band != last[0]) | (key != last[1]))[-1:].sum() + 1) if (band[0], key[0]) != last else 0
            if tail:
                yield from work(pa.Table.from_batches([*held, x.slice(0, tail)]))
                held = []
            held.append(x.slice(tail))
        if held:
            yield from work(pa.Table.from_batches(held))

    return run


def screen(similarity: float):
    """Rows (a, b, sketch, sketch) -> (a, b, sure) without the pairs below the bar; not sure: the full sets must decide."""

    def run(batches):
        for b in batches:
            keep, sure = [], []
            for x, y in zip(b.column(2).to_pylist(), b.column(3).to_pylist()):
                p, q = np.frombuffer(x, np.uint32), np.frombuffer(y, np.uint32)
                part = len(p) == SKETCH or len(q) == SKETCH
                if part:  # least SKETCH hashes of the union
                    union = np.union1d(p, q)[:SKETCH]
                    common = np.intersect1d(np.intersect1d(p, q, True), union, True)
                    j = len(common) / max(1, len(union))
                else:
                    common = len(np.intersect1d(p, q, True))
                    j = common / max(1, len(p) + len(q) - common)
                keep.append(j >= similarity - MARGIN * part)
                sure.append(not part)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(sure, pa.bool_())], names=["a", "b", "sure"]).filter(pa.array(keep, pa.bool_()))

    return run


def word_key(text: str):
    """Hash of the word sequence."""
    return F.sha2(F.array_join(words_of(ascii_lower(whole_text(text))), " "), 256)


def shingle_sets(asked: DataFrame, docs: DataFrame, classes: DataFrame, text: str, doc_id: str, k: int) -> DataFrame:
    """(rep, s): the distinct shingles of the asked(rep); only their texts are read again."""
    asked = materialize(classes.join(asked, "rep", "left_semi").select("rep", "wh"))
    again = docs.select(F.col(doc_id).alias("rep"), F.col(text).alias("t")).join(asked.select("rep").distinct().hint("merge"), "rep", "left_semi")
    again = again.withColumn("wh", word_key("t")).dropDuplicates(["rep", "wh"]).join(asked.hint("merge"), ["rep", "wh"], "left_semi")
    return materialize(again.select("rep", F.array_distinct(shingle_hashes(whole_text("t"), k)).alias("s")))


def decided(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """Pairs (a, b) whose full sets of distinct shingles are at the bar."""
    x, y = sets.select(F.col("rep").alias("a"), F.col("s").alias("x")), sets.select(F.col("rep").alias("b"), F.col("s").alias("y"))
    both = pairs.join(x, "a").join(y, "b").withColumn("common", F.size(F.array_intersect("x", "y")))
    return both.where(F.col("common") >= similarity * (F.size("x") + F.size("y") - F.col("common")) - 1e-9).select("a", "b")


def near_duplicate_groups(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", k: int = 5, similarity: float = 0.8) -> DataFrame:
    """d (the doc_id) and root (least doc_id of its group) of every row with an id; equal word sequences are one class."""
    all_rows = materialize(profiles(docs.where(F.col(doc_id).isNotNull()), doc_id, text, k))
    classes = all_rows.groupBy("wh").agg(F.min("d").alias("rep"), F.first("fp").alias("fp"), F.first("bands").alias("bands"), F.first("sketch").alias("sketch"), F.first("n").alias("n"), F.first("minima").alias("minima"))
    classes = materialize(classes)
    slim = materialize(all_rows.select("d", "wh"))
    forget(all_rows)
    texts = classes.where("n > 0")
    # SimHash: equal fingerprints, then covering links between fingerprints
    fps = texts.groupBy("fp").agg(F.min("rep").alias("least"))
    same = texts.join(fps, "fp").where("rep <> least").select(F.col("rep").alias("a"), F.col("least").alias("b"))
    links = class_links(fps.select("fp"))
    cover = links.join(fps.select(F.col("fp").alias("a"), F.col("least").alias("x")), "a").join(fps.select(F.col("fp").alias("b"), F.col("least").alias("y")), "b").select(F.col("x").alias("a"), F.col("y").alias("b"))
    # bands
    rows = texts.select("rep", F.shiftright("fp", 56).alias("part"), F.posexplode("bands").alias("band", "key"))
    parts = rows.groupBy("band", "key", "part").agg(F.min("rep").alias("first"), F.count(F.lit(1)).alias("m"))
    least = parts.groupBy("band", "key").agg(F.min("first").alias("least"), F.sum("m").alias("m")).where("m > 1").drop("m")
    heads = parts.drop("m").join(least, ["band", "key"])  # the first of each part of a bucket meets the bucket's first,
    shared = rows.join(heads.drop("least"), ["band", "key", "part"])  # the others the first of their part
    banded = shared.select(F.col("rep").alias("a"), F.col("first").alias("b")).union(heads.select(F.col("first").alias("a"), F.col("least").alias("b")))
    pairs = same.union(cover).union(banded).where("a is not null and b is not null and a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    pair_type = f"a {dict(docs.dtypes)[doc_id]}, b {dict(docs.dtypes)[doc_id]}"
    sets = texts.select("rep", "sketch")

    def verified(pairs):
        both = pairs.join(sets.select(F.col("rep").alias("a"), F.col("sketch").alias("x")), "a").join(sets.select(F.col("rep").alias("b"), F.col("sketch").alias("y")), "b").select("a", "b", "x", "y")
        seen = materialize(both.mapInArrow(screen(similarity), f"{pair_type}, sure boolean"))
        good, unsure = seen.where("sure").select("a", "b"), seen.where("not sure").select("a", "b")
        if not unsure.limit(1).count():
            return good
        asked = unsure.select(F.explode(F.array("a", "b")).alias("rep")).distinct()
        return good.union(decided(unsure, shingle_sets(asked, docs, classes, text, doc_id, k), similarity))

    nodes = materialize(components(verified(pairs)))
    # buckets whose documents are in several groups so far
    label = texts.select("rep", "bands").join(nodes.withColumnRenamed("node", "rep"), "rep", "left").select("rep", F.coalesce("root", "rep").alias("label"), F.posexplode("bands").alias("band", "key"))
    label = materialize(label)
    mixed = label.groupBy("band", "key").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo <> hi").select("band", "key")
    members = materialize(label.join(mixed, ["band", "key"]))
    sets = shingle_sets(members.select("rep").distinct(), docs, classes, text, doc_id, k)
    forget(label)
    full = members.join(texts.select("rep", "n", "minima").join(sets, "rep"), "rep").select("band", "key", "rep", "label", "n", "minima", "s")
    crossed = full.repartition("band", "key").sortWithinPartitions("band", "key").mapInArrow(cross_links(similarity), pair_type)
    nodes = components(materialize(crossed).union(nodes.select(F.col("node").alias("a"), F.col("root").alias("b"))))
    named = classes.select("wh", "rep").join(nodes.withColumnRenamed("node", "rep"), "rep", "left").select("wh", F.coalesce("root", "rep").alias("root"))
    return slim.join(named, "wh").select("d", "root")
