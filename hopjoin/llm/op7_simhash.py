"""SimHash near-duplicates by covering locality-sensitive hashing.

Shingle hashes are made on the JVM (XXH64, seed 42); a bit of the fingerprint is the majority of its column.  Equal
fingerprints are one class, so any number of copies costs one row from here on.

Covering masks: bit i of the fingerprint carries a nonzero code phi(i) of radius+1 bits; mask v keeps the bits whose code
has odd overlap with v.  At most `radius` differing bits put at most `radius` linear conditions on v, so some nonzero v
hides them all: every pair within the radius agrees under one of the 2**(radius+1)-1 masks.

Buckets (mask, masked value) are streamed in sorted order; inside a bucket of at most BUCKET classes all pairs are compared
in place and only a spanning forest leaves the task.  Classes of larger buckets go another exact way that never compares
pairs: each class is listed under itself and its one-bit neighbours, and all classes under one such centre (65 at most)
are within two bits of each other.  For radius 2 this finds every link.  Components are joined by star rounds.

Defined results: null or wordless texts have fingerprint zero and link like any other; fewer words than a shingle are one
shingle; repeated rows share a class; a null id is never a component's least id unless there is no other; an empty table
gives no rows; long texts are hashed whole, with counts added up in blocks.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower, components, let, materialize, table, whole_text, words_of

BUCKET = 256
BITS = 64


def shingle_hashes(text: Column, k: int) -> Column:
    """array<bigint>: XXH64 (seed 42) of the k-word shingles, repeats included."""

    def of(ws: Column) -> Column:
        many = F.transform(F.sequence(F.lit(0), F.size(ws) - k), lambda i: F.xxhash64(F.concat_ws(" ", *[F.get(ws, i + j) for j in range(k)])))
        return F.when(F.size(ws) >= k, many).when(F.size(ws) > 0, F.array(F.xxhash64(F.array_join(ws, " ")))).otherwise(F.array().cast("array<bigint>"))

    return let(words_of(ascii_lower(text)), of)


def majority(values: np.ndarray, offsets: np.ndarray, step: int = 1 << 17) -> np.ndarray:
    """uint64 fingerprints of the lists values[offsets[i]:offsets[i+1]]."""
    n = len(offsets) - 1
    counts = np.zeros((n, BITS), dtype=np.int64)
    lo, first, last = int(offsets[0]), int(offsets[0]), int(offsets[-1])
    while first < last:
        end = min(first + step, last)
        bits = np.unpackbits(values[first - lo : end - lo].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
        a = int(np.searchsorted(offsets, first, "right")) - 1
        b = int(np.searchsorted(offsets, end, "left"))
        starts = np.maximum(offsets[a:b], first) - first
        keep = np.flatnonzero(offsets[a + 1 : b + 1] > np.maximum(offsets[a:b], first))
        counts[a:b][keep] += np.add.reduceat(bits, starts[keep], axis=0, dtype=np.int64)
        first = end
    ones = counts * 2 > (offsets[1:] - offsets[:-1])[:, None]
    return np.packbits(ones, axis=1).view(">u8").reshape(-1).astype(np.uint64)


def fingerprints(docs: DataFrame, keys: list[str], text: str = "text", k: int = 3) -> DataFrame:
    """keys and fp (the fingerprint as a signed long)."""
    hashed = docs.select(*keys, shingle_hashes(whole_text(text), k).alias("__h"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*keys).schema) + ", fp bigint"

    def run(batches):
        for b in batches:
            h = b.column("__h")
            if not b.num_rows:
                continue
            offsets = np.asarray(h.offsets, dtype=np.int64)
            fp = majority(np.asarray(h.values)[offsets[0] : offsets[-1]].view(np.uint64) if len(h.values) else np.zeros(0, np.uint64), offsets)
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in keys], pa.array(fp.view(np.int64))], names=[*keys, "fp"])

    return hashed.mapInArrow(run, schema)


def covering_masks(radius: int, bits: int = BITS) -> list[int]:
    """The masks as signed longs."""
    top = (1 << (radius + 1)) - 1
    phi = [(i * 5 + i // top) % top + 1 for i in range(bits)]
    masks = [sum(1 << i for i in range(bits) if bin(phi[i] & v).count("1") % 2) for v in range(1, top + 1)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def _forest(fp: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Star edges (value, least value) of the components of index pairs a, b."""
    label = np.arange(len(fp))
    while True:
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        new = new[new]
        if np.array_equal(new, label):
            break
        label = new
    moved = np.flatnonzero(label != np.arange(len(fp)))
    return fp[moved], fp[label[moved]]


def bucket_links(radius: int, limit: int = BUCKET):
    """mapInArrow function over rows (v, key, fp) sorted by (v, key, fp): kind 0 rows are links, kind 1 rows are classes of large buckets."""

    def out(kind, a, b):
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(a), kind, np.int32)), pa.array(a), pa.array(b)], names=["kind", "a", "b"])

    def work(v, key, fp):
        new = np.flatnonzero(np.r_[True, (v[1:] != v[:-1]) | (key[1:] != key[:-1])])
        size = np.diff(np.r_[new, len(fp)])
        group = np.repeat(np.arange(len(new)), size)
        big = size[group] > limit
        if big.any():
            yield out(1, fp[big], fp[big])
        left = (size[group] - (np.arange(len(fp)) - new[group])) * ~big  # rows from here to the end of the bucket
        pairs_a, pairs_b, d = [], [], 1
        at = np.flatnonzero(left > d)
        while len(at):
            x = (fp[at] ^ fp[at + d]).view(np.uint64)
            near = np.bitwise_count(x) <= radius
            pairs_a.append(at[near])
            pairs_b.append(at[near] + d)
            d += 1
            at = at[left[at] > d]
        if pairs_a:
            a, b = np.concatenate(pairs_a), np.concatenate(pairs_b)
            if len(a):
                yield out(0, *_forest(fp, a, b))

    def run(batches):
        held, streaming = None, None  # rows of the last, unfinished bucket; the key of a bucket known to be large
        for batch in batches:
            cols = [np.asarray(batch.column(i)) for i in range(3)]
            if streaming is not None:
                same = (cols[0] == streaming[0]) & (cols[1] == streaming[1])
                if same.any():
                    yield out(1, cols[2][same], cols[2][same])
                    cols = [c[~same] for c in cols]
                if not len(cols[0]):
                    continue
                streaming = None
            if held is not None:
                cols = [np.concatenate([h, c]) for h, c in zip(held, cols)]
            v, key, fp = cols
            if not len(v):
                continue
            tail = (v == v[-1]) & (key == key[-1])
            if tail.sum() > limit:
                streaming, held = (v[-1], key[-1]), None
                yield from work(v, key, fp)
                continue
            held = [c[tail] for c in cols]
            if not tail.all():
                yield from work(v[~tail], key[~tail], fp[~tail])
        if held is not None:
            yield from work(*held)

    return run


def _centre_stars(batches):
    """Rows (z, fp) sorted by z, fp: links of each class to the first class under the same centre."""
    last_z, last_fp = None, None
    for b in batches:
        z, fp = np.asarray(b.column(0)), np.asarray(b.column(1))
        if not len(z):
            continue
        new = np.r_[True, z[1:] != z[:-1]]
        first = np.maximum.accumulate(np.where(new, np.arange(len(z)), 0))
        head = fp[first]
        if last_z is not None and z[0] == last_z:
            head = np.where(first == 0, last_fp, head)
        last_z, last_fp = z[-1], head[-1]
        keep = head != fp
        if keep.any():
            yield pa.RecordBatch.from_arrays([pa.array(fp[keep]), pa.array(head[keep])], names=["a", "b"])


def class_links(classes: DataFrame, radius: int = 2) -> DataFrame:
    """classes(fp), distinct -> links (a, b) whose components are those of all pairs within the radius (2 at most)."""
    if radius not in (0, 1, 2):
        raise ValueError("radius must be 0, 1 or 2")
    masks = covering_masks(radius)
    keys = F.array(*[F.struct(F.lit(v).alias("v"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for v, m in enumerate(masks)])
    rows = classes.select(F.explode(keys).alias("k"), "fp").select("k.v", "k.key", "fp")
    found = materialize(rows.repartition("v", "key").sortWithinPartitions("v", "key", "fp").mapInArrow(bucket_links(radius), "kind int, a bigint, b bigint"))
    links = found.where("kind = 0").select("a", "b")
    large = found.where("kind = 1").select(F.col("a").alias("fp")).distinct()
    flips = [F.col("fp")] + [F.col("fp").bitwiseXOR(F.lit((1 << i) if i < 63 else -(1 << 63))) for i in range(BITS)]
    if radius < 2:  # centres join pairs at distance two: compare what they give
        flips = flips if radius == 1 else flips[:1]
    centred = large.select(F.explode(F.array(*flips)).alias("z"), "fp").repartition("z").sortWithinPartitions("z", "fp").mapInArrow(_centre_stars, "a bigint, b bigint")
    if radius == 1:
        centred = large.select(F.explode(F.array(*flips[1:])).alias("b"), F.col("fp").alias("a")).join(large.select(F.col("fp").alias("b")), "b", "left_semi").select("a", "b")
    return links.union(centred)


def near_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", k: int = 3, radius: int = 2) -> DataFrame:
    """doc_id, fp and component_id (least doc_id of the component) of every row."""
    prints = materialize(fingerprints(docs, [doc_id], text, k))
    classes = materialize(prints.groupBy("fp").agg(F.min(doc_id).alias("least")))
    nodes = components(class_links(classes.select("fp"), radius))
    named = classes.join(nodes.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    least = named.groupBy("root").agg(F.min("least").alias("component_id"))
    return prints.join(named.join(least, "root").select("fp", "component_id"), "fp").select(doc_id, "fp", "component_id")


def op7_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
