"""Benchmark decontamination by winnowing.

Texts are tokenised as bytes (a word is a run of 0-9, a-z after lower-casing A-Z, and bytes above 0x7F) and each word is a
64-bit polynomial hash.  Both sides hash all GRAM-word grams and keep, per run of WINDOW-GRAM+1 grams, the leftmost least
one: a span of WINDOW equal words has the same kept gram on both sides, so no shared span is missed.  Kept grams that meet
are extended word by word to either side; a run of WINDOW or more words is hit.  Items shorter than a window are matched
whole, in tables of their own, from their first gram of GRAM words or, if they are shorter, of their own length.

The benchmark is the stated query set: it is gathered in blocks of at most BLOCK_BYTES of text, each block is shipped to
every task, and the documents are read once per block (one block unless the benchmark is larger than that); hits of
several blocks are united per document row.  Documents are never shuffled in the one-block case.

Defined results: a null or wordless document has n_words 0 and is clean; a null or wordless item is never found; items with
equal text are all reported; repeated rows give repeated results; an empty benchmark leaves every document clean; very long
texts are processed whole, in chunks cut between words; a null item_id counts as the empty id.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import safe_prefix, table

WINDOW = 13
GRAM = 5
BLOCK_BYTES = 32 << 20
#: bytes of text that are hashed at once, and bytes of an Arrow batch that are looked up at once
STEP, SLICE_BYTES = 1 << 19, 1 << 21

_U = np.uint64
_MULT, _INV = 0x9E3779B97F4A7C15, pow(0x9E3779B97F4A7C15, -1, 1 << 64)


def _byte_values() -> np.ndarray:
    """Odd pseudo-random weight of each byte, upper case folded; 0 marks a separator."""
    x = np.arange(256, dtype=_U)
    x[65:91] += _U(32)
    v = (x + _U(1)) * _U(0xD6E8FEB86659FD93)
    v ^= v >> _U(29)
    v = (v * _U(0xA3B195354A39B70D)) | _U(1)
    word = np.zeros(256, bool)
    word[48:58] = word[65:91] = word[97:123] = word[128:] = True
    return np.where(word, v, _U(0))


VALUES = _byte_values()


def _powers(base: int, n: int) -> np.ndarray:
    return np.cumprod(np.r_[_U(1), np.full(max(n - 1, 0), base, _U)])[:n] if n else np.zeros(0, _U)


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> _U(31))) * _U(0x7FB5D329728EA185)
    return h ^ (h >> _U(27))


def _chunk_end(data: np.ndarray, bounds: np.ndarray, lo: int, step: int) -> int:
    """About lo + step, at the end of a string or just behind a separator, so that no word is cut."""
    hi = lo + step
    if hi >= len(data):
        return len(data)
    inner = int(bounds[np.searchsorted(bounds, hi, "right") - 1])
    for near in (min(step, 4096), step):
        marks = np.flatnonzero(VALUES[data[hi - near : hi]] == 0)
        back = max(inner, hi - near + int(marks[-1]) + 1 if len(marks) else lo)
        if back > lo:
            return back
    stop = int(bounds[np.searchsorted(bounds, hi, "left")])
    while hi < stop:  # one word longer than a chunk
        marks = np.flatnonzero(VALUES[data[hi : min(stop, hi + step)]] == 0)
        if len(marks):
            return hi + int(marks[0]) + 1
        hi += step
    return stop


def word_hashes(data: np.ndarray, bounds: np.ndarray, step: int = STEP) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words of the byte strings data[bounds[i]:bounds[i+1]], and the words' counts per string.

    The bytes are read in chunks of about `step`, cut between words: scratch memory depends on neither batch nor text.
    """
    hashes, begun, lo = [], [], 0
    powers, inverse = (_powers(x, min(step, len(data)) + 1) for x in (_MULT, _INV))
    while lo < len(data):
        hi = _chunk_end(data, bounds, lo, step)
        v = VALUES[data[lo:hi]]
        on = v != 0
        begins = on.copy()
        begins[1:] &= ~on[:-1]
        cut = bounds[np.searchsorted(bounds, lo, "right") : np.searchsorted(bounds, hi, "left")] - lo
        begins[cut] |= on[cut]
        starts = np.flatnonzero(begins)
        ends_at = on.copy()
        ends_at[:-1] &= ~on[1:] | begins[1:]
        ends = np.flatnonzero(ends_at) + 1
        if hi - lo >= len(powers):
            powers, inverse = (_powers(x, hi - lo + 1) for x in (_MULT, _INV))
        v *= powers[: hi - lo]
        sums = np.zeros(hi - lo + 1, _U)
        np.cumsum(v, out=sums[1:])
        h = (sums[ends] - sums[starts]) * inverse[starts]
        hashes.append(_mix(h + (ends - starts).astype(_U) * _U(0xC2B2AE3D27D4EB4F)))
        begun.append(starts + lo)
        lo = hi
    starts = np.concatenate(begun) if begun else np.zeros(0, np.int64)
    return (np.concatenate(hashes) if hashes else np.zeros(0, _U)), np.diff(np.searchsorted(starts, bounds))


def grams(words: np.ndarray, n: int) -> np.ndarray:
    """Hash of each n consecutive words (crossing strings too: runs are cut when hits are extended)."""
    if len(words) < n:
        return np.zeros(0, _U)
    h = words[: len(words) - n + 1].copy()
    for j in range(1, n):
        h = h * _U(0x9FB21C651E98DF25) + words[j : len(words) - n + 1 + j]
    return _mix(h)


def winnow(h: np.ndarray, width: int) -> np.ndarray:
    """Positions that are the leftmost least of some `width` consecutive hashes."""
    n = len(h)
    if n <= width:
        return np.unique(np.argmin(h)[None]) if n else np.zeros(0, np.int64)
    windows = np.lib.stride_tricks.sliding_window_view(h, width)
    return np.unique(np.argmin(windows, axis=1) + np.arange(n - width + 1))


class Index:
    """Word hashes of a block of items, with their fingerprints in sorted order."""

    def __init__(self, items: list[tuple[int, bytes]], window: int = WINDOW, gram: int = GRAM):
        data = np.frombuffer(b"".join(t for _, t in items), np.uint8)
        bounds = np.cumsum([0] + [len(t) for _, t in items])
        self.window, self.gram = window, gram
        self.words, counts = word_hashes(data, bounds)
        self.begin = np.r_[0, np.cumsum(counts)]
        self.item_of = np.repeat(np.arange(len(items)), counts)
        self.need = np.minimum(counts, window)  # words that must agree
        self.ids = [i for i, _ in items]
        #: (words of a gram, whether documents look up winnowed positions only) -> sorted hashes and their places
        self.tables = {}
        groups: dict[tuple[int, bool], list[int]] = {}
        for k, n in enumerate(counts):
            if n:
                groups.setdefault((int(min(n, gram)), bool(n >= window)), []).append(k)
        for (size, long), mine in groups.items():
            h = grams(self.words, size)
            if long:
                at = winnow(h, window - gram + 1)
                ours = np.zeros(len(items), bool)
                ours[mine] = True
                at = at[ours[self.item_of[at]] & (self.item_of[at] == self.item_of[at + size - 1])]
            else:
                at = self.begin[mine]  # found whole from the first gram
            order = np.argsort(h[at], kind="stable")
            self.tables[size, long] = (h[at][order], at[order])


def find(index: Index, words: np.ndarray, counts: np.ndarray):
    """Hit words (bool per word) and the pairs (string, item) with an occurring window."""
    hit = np.zeros(len(words) + 1, np.int64)
    pairs = []
    begin = np.r_[0, np.cumsum(counts)]
    owner = np.repeat(np.arange(len(counts)), counts)
    for (size, long), (known, places) in index.tables.items():
        h = grams(words, size)
        # strings are joined end to end: windows at their seams only add positions
        at = winnow(h, index.window - index.gram + 1) if long else np.arange(len(h))
        at = at[owner[at] == owner[at + size - 1]] if len(at) else at
        lo = np.searchsorted(known, h[at], "left")
        n = np.searchsorted(known, h[at], "right") - lo
        for part in np.array_split(np.flatnonzero(n), max(1, int(n.sum()) >> 20)):
            if not len(part):
                continue
            m = n[part]
            p = np.repeat(at[part], m)
            q = places[np.repeat(lo[part] - np.r_[0, np.cumsum(m)[:-1]], m) + np.arange(m.sum())]
            s, k = owner[p], index.item_of[q]
            a, b = _extend(words, index.words, p, q, begin[s], index.begin[k], -1, index.window), _extend(words, index.words, p + size - 1, q + size - 1, begin[s + 1] - 1, index.begin[k + 1] - 1, 1, index.window)
            ok = a + size + b >= index.need[k]
            same = _same(words, index.words, p, q, size)
            ok &= same
            np.add.at(hit, p[ok] - a[ok], 1)
            np.add.at(hit, p[ok] + size + b[ok], -1)
            pairs.append(np.unique(s[ok] * len(index.ids) + k[ok]))
    found = np.unique(np.concatenate(pairs)) if pairs else np.zeros(0, np.int64)
    return np.cumsum(hit)[:-1] > 0, found // max(1, len(index.ids)), found % max(1, len(index.ids))


def _same(x, y, p, q, size):
    out = np.ones(len(p), bool)
    for j in range(size):
        out &= x[p + j] == y[q + j]
    return out


def _extend(x, y, p, q, stop_p, stop_q, way, most):
    """How many words beyond p and q agree in direction `way`, at most `most`."""
    n = np.zeros(len(p), np.int64)
    live = np.arange(len(p))
    for j in range(1, most + 1):
        i, k = p[live] + way * j, q[live] + way * j
        inside = ((i <= stop_p[live]) & (k <= stop_q[live])) if way > 0 else ((i >= stop_p[live]) & (k >= stop_q[live]))
        live, i, k = live[inside], i[inside], k[inside]
        live = live[x[i] == y[k]]
        if not len(live):
            break
        n[live] = j
    return n


def _arrow_bytes(column) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and the bounds of its strings (null: empty)."""
    if column.null_count:
        column = column.fill_null("")
    wide = column.type in (pa.large_string(), pa.large_binary())
    _, offsets, data = column.buffers()
    bounds = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[bounds[0] : bounds[-1]], bounds - bounds[0]


def sliced(batch: pa.RecordBatch, column: str, limit: int | None = None):
    """The batch in runs of rows of about `limit` bytes of a string column (a longer text alone)."""
    limit = limit or SLICE_BYTES
    if not batch.num_rows:
        return
    _, bounds = _arrow_bytes(batch.column(column))
    first = 0
    while first < batch.num_rows:
        last = max(first + 1, int(np.searchsorted(bounds, bounds[first] + limit, "right")) - 1)
        yield batch.slice(first, last - first)
        first = last


def benchmark_blocks(benchmark: DataFrame, item_id: str, text: str, block_bytes: int = BLOCK_BYTES) -> list[DataFrame]:
    """The benchmark in blocks of at most about block_bytes of text, dealt by a hash of the item's id."""
    total = benchmark.agg(F.coalesce(F.sum(F.octet_length(text)), F.lit(0))).first()[0]
    n = int(total // block_bytes) + 1
    slim = benchmark.where(F.col(text).isNotNull()).select(F.col(item_id).cast("string").alias("i"), F.col(text).alias("t"))
    return [slim] if n == 1 else [slim.where(F.pmod(F.xxhash64("i"), F.lit(n)) == k) for k in range(n)]


def overlaps(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = WINDOW, gram: int = GRAM) -> tuple[DataFrame, str]:
    """docs' columns with <p>n_words, <p>n_hit and <p>items (sorted ids of the items with an occurring window)."""
    p = safe_prefix(docs, "bd")
    blocks = benchmark_blocks(benchmark, item_id, item_text)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema) + f", `{p}n_words` bigint, `{p}n_hit` bigint, `{p}items` array<string>, `{p}runs` array<bigint>"
    spark = docs.sparkSession

    def scan(block: DataFrame, with_runs: bool, source: DataFrame) -> DataFrame:
        items = sorted((r.i or "", r.t.encode()) for r in block.collect())  # at most BLOCK_BYTES of text
        shipped = spark.sparkContext.broadcast(vars(Index(items, window, gram)))  # plain arrays, made once

        def run(batches):
            index = object.__new__(Index)
            index.__dict__ = shipped.value
            for b in (part for batch in batches for part in sliced(batch, text)):
                words, counts = word_hashes(*_arrow_bytes(b.column(text)))
                hit, s, k = find(index, words, counts)
                begin = np.r_[0, np.cumsum(counts)]
                sums = np.r_[0, np.cumsum(hit)]
                found = [[] for _ in range(b.num_rows)]
                for i, j in zip(s.tolist(), k.tolist()):
                    found[i].append(index.ids[j])
                runs = [[]] * b.num_rows
                if with_runs:
                    runs = [np.flatnonzero(np.diff(np.r_[0, hit[begin[i] : begin[i + 1]].astype(np.int8), 0])).tolist() for i in range(b.num_rows)]
                new = [pa.array(counts), pa.array(sums[begin[1:]] - sums[begin[:-1]]), pa.array([sorted(set(x)) for x in found], pa.list_(pa.string())), pa.array(runs, pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays([*b.columns, *new], names=[*b.schema.names, f"{p}n_words", f"{p}n_hit", f"{p}items", f"{p}runs"])

        return source.mapInArrow(run, schema)

    if len(blocks) == 1:
        return scan(blocks[0], False, docs).drop(f"{p}runs"), p
    # several blocks: every block's runs of hit words are united per document row
    row = f"{p}row"
    slim = docs.select(text).where(F.col(text).isNotNull()).distinct()
    inner = None
    schema_docs, schema = schema, ", ".join([f"`{text}` string", f"`{p}n_words` bigint, `{p}n_hit` bigint, `{p}items` array<string>, `{p}runs` array<bigint>"])
    for block in blocks:
        one = scan(block, True, slim).where(F.size(f"{p}items") > 0).select(F.sha2(text, 256).alias(row), f"{p}items", f"{p}runs")
        inner = one if inner is None else inner.union(one)
    both = inner.groupBy(row).agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list(f"{p}items")))).alias(f"{p}items"), F.flatten(F.collect_list(f"{p}runs")).alias(f"{p}runs"))
    ends = F.transform(F.sequence(F.lit(0), F.size(f"{p}runs") - 2, F.lit(2)), lambda i: F.struct(F.get(F.col(f"{p}runs"), i).alias("s"), F.get(F.col(f"{p}runs"), i + 1).alias("e")))
    merged = F.aggregate(F.array_sort(ends), F.struct(F.lit(0).cast("long").alias("at"), F.lit(0).cast("long").alias("n")), lambda a, x: F.struct(F.greatest(a["at"], x["e"]).alias("at"), (a["n"] + F.greatest(F.lit(0).cast("long"), x["e"] - F.greatest(a["at"], x["s"]))).alias("n")), lambda a: a["n"])
    both = both.select(row, F.col(f"{p}items"), merged.alias(f"{p}n_hit"))
    count = F.regexp_count(F.coalesce(F.col(text), F.lit("")), F.lit(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")).cast("long")
    out = docs.withColumn(row, F.sha2(text, 256)).join(both, row, "left").withColumn(f"{p}n_words", count)
    out = out.select(*docs.columns, f"{p}n_words", F.coalesce(f"{p}n_hit", F.lit(0).cast("long")).alias(f"{p}n_hit"), F.coalesce(f"{p}items", F.array().cast("array<string>")).alias(f"{p}items"))
    return out, p


def contaminated(p: str):
    """The contract's rule: some word is hit, and at least a twentieth of all words are."""
    return (F.col(f"{p}n_hit") > 0) & (20 * F.col(f"{p}n_hit") >= F.col(f"{p}n_words"))


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    out, p = overlaps(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))
    items = F.col(f"{p}items")
    return out.select("doc_id", F.col(f"{p}n_words").alias("n_words"), F.col(f"{p}n_hit").alias("n_hit"), F.size(items).cast("long").alias("n_items"), F.sha2(F.array_join(items, ","), 256).alias("items_sha256"), contaminated(p).alias("contaminated"))


def oracle(docs: str = "documents") -> str:
    """The same rows in DuckDB: every window of every item joined with every window of every document."""
    word = "'[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+'"
    low = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    return f"""
    WITH d AS (SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all({low}, {word}) AS ws FROM {docs}),
    b AS (SELECT item_id, regexp_extract_all({low}, {word}) AS ws FROM benchmark),
    bw AS (SELECT item_id, least(len(ws), {WINDOW}) AS n, ws[i:i + least(len(ws), {WINDOW}) - 1] AS win FROM (SELECT item_id, ws, unnest(range(1, len(ws) - least(len(ws), {WINDOW}) + 2)) AS i FROM b WHERE len(ws) > 0)),
    sizes AS (SELECT DISTINCT n FROM bw),
    dw AS (SELECT rid, n, i, ws[i:i + n - 1] AS win FROM (SELECT rid, n, ws, unnest(range(1, len(ws) - n + 2)) AS i FROM d CROSS JOIN sizes WHERE len(ws) >= n)),
    m AS (SELECT DISTINCT rid, i, dw.n, item_id FROM dw JOIN bw USING (n, win)),
    spots AS (SELECT DISTINCT rid, i, n FROM m),
    hits AS (SELECT rid, count(DISTINCT w) AS n_hit FROM (SELECT rid, unnest(range(i, i + n)) AS w FROM spots) GROUP BY rid),
    its AS (SELECT rid, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS ids FROM (SELECT rid, item_id::VARCHAR AS item FROM m GROUP BY rid, item_id) GROUP BY rid)
    SELECT doc_id, len(ws)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(ids, '')) AS items_sha256,
        coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated
    FROM d LEFT JOIN hits USING (rid) LEFT JOIN its USING (rid)"""
