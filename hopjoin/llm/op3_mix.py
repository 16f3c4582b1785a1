"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree (native DataFrame operations only).

1. Every document gets a permutation key from a digest of its id; the key's leading bits name a block of its source.
2. Source targets: weights in source order share `share` of all words; a target stops at `cap` times its source, what is
   left over goes to the others by weight until none is above (closed form over the sorted cap-to-weight ratios).
3. A source is drawn whole floor(target / size) times; the rest is a run of permuted blocks, the last one cut inside.  A
   document that is longer than what is still wanted is skipped and the run goes on behind it, as long as PICKS of the
   largest documents that fit would not fill the gap; those follow, and one that overshoots if that comes nearer.
4. The block draws of all sources are dealt to output shards by a binary tree: at each node the left half's count of each
   source is drawn from the multivariate hypergeometric law (sequential sampling with hashed uniforms: same rows, same
   draw, whatever the partitioning).  A shard then takes the next disjoint run of permuted blocks of each source and is
   shuffled locally.

Blocks and shards grow with the data: about BLOCKS_PER_SHARD blocks of each source a shard, up to MAX_CELLS cells (source,
block) and 2**MAX_LEVELS shards; the cells go to the documents by broadcast up to BROADCAST_CELLS and by a join beyond.
Only the tree's counts per source, and one row per source, meet in single tasks.

Defined results: a null text has size 0, a null source is a source of its own (last in order), a null id hashes like an
empty one; equal ids share a key and are taken together; an empty table gives an empty mix; a source without words has
target 0 and is never drawn.  Other columns pass through untouched, whatever they are called.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WORD_CLASS, materialize, safe_prefix, table, whole_text

WEIGHTS = (5, 2, 1)
KEY_BITS = 60
MAX_CELLS, BROADCAST_CELLS = 1 << 22, 65_536
MAX_LEVELS, BLOCKS_PER_SHARD, LEAST_CELLS = 19, 8, 4096
#: rounds of skipping documents that do not fit, at most; the oracle has so many of them
SKIPS = 16
#: single documents behind the runs, the largest that fit
PICKS = 6


def permutation_key(doc_id: Column, seed: int) -> Column:
    """60 bits of the MD5 of seed and id."""
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.lit(""))))
    return F.conv(F.substring(digest, 1, KEY_BITS // 4), 16, 10).cast("long")


def source_targets(sources: DataFrame, weights=WEIGHTS, share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """sources(skey, source, source_size) -> the same with target.  One row per source: metadata, hence one window."""
    every = Window.partitionBy(F.lit(0))
    by_name = every.orderBy(F.col("source").asc_nulls_last())
    by_ratio = every.orderBy("ratio", "skey")
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    rest = by_ratio.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.row_number().over(by_name) - 1) % len(weights) + 1)
    s = sources.withColumn("w", w).withColumn("most", cap * F.col("source_size"))
    s = s.withColumn("ratio", F.col("most") / F.col("w"))
    s = s.withColumn("level", (share * F.sum("source_size").over(every) - F.coalesce(F.sum("most").over(before), F.lit(0.0))) / F.sum("w").over(rest))
    s = s.withColumn("free", F.col("level") * F.col("w") <= F.col("most")).withColumn("at", F.row_number().over(by_ratio))
    s = s.withColumn("level", F.min(F.when(F.col("free"), F.struct("at", "level"))).over(every)["level"])
    target = F.when(F.col("level").isNull(), F.col("most")).otherwise(F.least("most", F.col("level") * F.col("w")))
    return s.select("skey", "source", "source_size", target.alias("target"))


def split_tree(quotas: DataFrame, levels: int, seed: int) -> DataFrame:
    """quotas(skey, n): draws per source -> (shard, skey, n) over 2**levels shards, all nodes of a level in one fold."""
    nodes = quotas.where("n > 0").select(F.lit(0).cast("long").alias("node"), "skey", F.col("n").cast("long").alias("n"))
    for _ in range(levels):
        packed = nodes.groupBy("node").agg(F.sort_array(F.collect_list(F.struct("skey", "n"))).alias("have"), F.sum("n").alias("pool"))

        def one_source(state, s):
            start = F.struct(state["room"].alias("room"), state["pool"].alias("pool"), F.lit(0).cast("long").alias("left"))

            def one_draw(a, i):
                u = F.pmod(F.xxhash64(F.lit(seed), F.col("node"), s["skey"], i), F.lit(1 << 52)) / float(1 << 52)
                take = F.when(u * a["pool"] < a["room"], F.lit(1)).otherwise(F.lit(0)).cast("long")
                return F.struct((a["room"] - take).alias("room"), (a["pool"] - 1).alias("pool"), (a["left"] + take).alias("left"))

            done = F.aggregate(F.sequence(F.lit(1).cast("long"), s["n"]), start, one_draw)
            return F.transform(F.array(done), lambda d: F.struct(d["room"].alias("room"), d["pool"].alias("pool"), F.concat(state["out"], F.array(F.struct(s["skey"].alias("skey"), d["left"].alias("l"), (s["n"] - d["left"]).alias("r")))).alias("out")))[0]

        start = F.struct(F.floor(F.col("pool") / 2).cast("long").alias("room"), F.col("pool").alias("pool"), F.array().cast("array<struct<skey:string,l:bigint,r:bigint>>").alias("out"))
        dealt = packed.select("node", F.explode(F.aggregate("have", start, one_source, lambda st: st["out"])).alias("x"))
        sides = F.explode(F.array(F.struct((F.col("node") * 2).alias("node"), F.col("x.skey").alias("skey"), F.col("x.l").alias("n")), F.struct((F.col("node") * 2 + 1).alias("node"), F.col("x.skey").alias("skey"), F.col("x.r").alias("n"))))
        nodes = dealt.select(sides.alias("y")).select("y.*").where("n > 0")
    return nodes.select(F.col("node").alias("shard"), "skey", "n")


def _run_on(units: DataFrame, plan: DataFrame, block: Column, bits: int, small, first: bool) -> DataFrame:
    """One more run of each open source: documents behind its cut that fit into what is left, in permuted order, while they fit.

    After the first, only sources run on that PICKS of the largest documents that fit would leave unfilled.

    plan(skey, ..., cut, left, runs, open): a run (lo, hi, g) takes the documents of size g at most with lo < u <= hi.
    """
    live = plan.where("open").select("skey", "cut", "left")
    behind = lambda sources: units.join(small(sources), "skey").where((F.col("u") > F.col("cut")) & (F.col("size") > 0) & (F.col("size") <= F.col("left"))).withColumn("block", block)
    if not first:
        live = materialize(live.join(behind(live).groupBy("skey").agg(F.max("size").alias("top")), "skey").where(F.col("left") > PICKS * F.col("top")).drop("top"))
    fits = behind(live)
    upto = F.sum("words").over(Window.partitionBy("skey").orderBy("block"))
    sums = fits.groupBy("skey", "block").agg(F.sum("size").alias("words"), F.max("u").alias("last")).withColumn("upto", upto).join(small(live), "skey")
    within = sums.where("upto <= left").groupBy("skey").agg(F.max("upto").alias("base"), F.max("last").alias("hi0"))
    edge = sums.where("upto > left and upto - words <= left").groupBy("skey").agg(F.min("block").alias("edge"), F.min_by(F.col("upto") - F.col("words"), "block").alias("before"))
    inside = fits.join(small(edge), "skey").where(F.col("block") == F.col("edge"))
    inside = inside.withColumn("cum", F.col("before") + F.sum("size").over(Window.partitionBy("skey").orderBy("u"))).where("cum <= left")
    inside = inside.groupBy("skey").agg(F.max("u").alias("hi1"), F.max("cum").alias("taken1"))
    step = within.join(inside, "skey", "full").select("skey", F.greatest("hi0", "hi1").alias("hi"), F.greatest("base", "taken1").alias("taken"))
    out = plan.join(step, "skey", "left")
    run = F.array(F.struct(F.col("cut").alias("lo"), F.col("hi"), F.col("left").alias("g")))
    moved = F.col("hi").isNotNull()
    return out.select(
        "skey", "source_size", "target", "full", F.coalesce("hi", "cut").alias("cut"), (F.col("left") - F.coalesce("taken", F.lit(0))).alias("left"),
        F.when(moved, F.concat("runs", run)).otherwise(F.col("runs")).alias("runs"), moved.alias("open"),
    )


def mix_plan(docs: DataFrame, text: str = "text", source: str = "source", doc_id: str = "doc_id", weights=WEIGHTS, share: float = 1.5, cap: float = 2.0, words_per_shard: int = 4_000_000, seed: int = 17) -> tuple[DataFrame, str]:
    """docs with helper columns <p>size, <p>source_size, <p>target, <p>u and <p>shards (one entry per copy the mix takes).

    Returns the frame and the prefix p.  The words of each text are counted once, into a slim table in the shared folder.
    """
    p = safe_prefix(docs, "mix")
    size = F.regexp_count(whole_text(text), F.lit(WORD_CLASS)).cast("long")
    skey = F.coalesce(F.concat(F.lit("s"), F.col(source).cast("string")), F.lit("n"))
    u = permutation_key(F.col(doc_id), seed)
    slim = docs.select(skey.alias("skey"), F.col(source).alias("source"), u.alias("u"), size.alias("size"))
    units = materialize(slim.groupBy("skey", "u").agg(F.first("source").alias("source"), F.sum("size").alias("size"), F.count(F.lit(1)).alias("n")))
    by_source = materialize(units.groupBy("skey").agg(F.first("source").alias("source"), F.sum("size").alias("source_size")))
    n_sources, total = by_source.agg(F.count(F.lit(1)), F.coalesce(F.sum("source_size"), F.lit(0))).first()
    levels = max(0, min(MAX_LEVELS, math.ceil(math.log2(max(1.0, share * total / words_per_shard)))))
    cells = min(MAX_CELLS, max(LEAST_CELLS * max(1, n_sources), n_sources * BLOCKS_PER_SHARD << levels))
    bits = max(0, int(math.log2(max(1, cells // max(1, n_sources)))))
    block = F.shiftright(F.col("u"), KEY_BITS - bits).cast("long")

    targets = source_targets(by_source, weights, share, cap)
    full = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    targets = targets.withColumn("full", full).withColumn("rest", F.col("target") - F.col("full") * F.col("source_size"))
    blocks = materialize(units.groupBy("skey", block.alias("block")).agg(F.lit(1).alias("one")).drop("one").join(targets.select("skey", "full"), "skey"))
    small = lambda df: F.broadcast(df) if n_sources <= 4096 else df  # noqa: E731  one row per source, counted above
    none = F.array().cast("array<struct<lo:bigint,hi:bigint,g:double>>")
    plan = targets.select("skey", "source_size", "target", "full", F.lit(-1).cast("long").alias("cut"), F.col("rest").alias("left"), none.alias("runs"), F.lit(True).alias("open"))
    plan = materialize(plan)
    for i in range(SKIPS):
        plan = materialize(_run_on(units, plan, block, bits, small, i == 0))
        if not plan.where("open").limit(1).count():
            break
    plan = materialize(plan.withColumn("picks", F.array().cast("array<bigint>")))
    for i in range(PICKS + 1):  # the last round may overshoot
        last = i == PICKS
        room = (F.col("size") > F.col("left")) & (F.col("size") < 2 * F.col("left")) if last else (F.col("size") > 0) & (F.col("size") <= F.col("left"))
        fits = units.join(small(plan.select("skey", "cut", "left", "picks")), "skey").where((F.col("u") > F.col("cut")) & room & ~F.array_contains("picks", F.col("u")))
        best = fits.groupBy("skey").agg((F.min if last else F.max)(F.struct("size", "u")).alias("b"))
        plan = materialize(plan.join(best, "skey", "left").select("skey", "source_size", "target", "full", "cut", "runs", (F.col("left") - F.coalesce(F.col("b.size"), F.lit(0))).alias("left"), F.when(F.col("b").isNull(), F.col("picks")).otherwise(F.concat("picks", F.array(F.col("b.u")))).alias("picks")))

    # draws: whole copies of each block, then the blocks up to the cut, then one draw for the single documents
    each = blocks.select("skey", "block", "full").join(plan.select("skey", "cut"), "skey")
    extra = F.when(F.col("block") <= F.shiftright(F.greatest(F.col("cut"), F.lit(0)), KEY_BITS - bits), F.when(F.col("cut") >= 0, 1).otherwise(0)).otherwise(0)
    copies = each.withColumn("c", F.explode(F.sequence(F.lit(0).cast("long"), F.col("full")))).where((F.col("c") < F.col("full")) | (extra == 1)).select("skey", "block", "c", (F.col("c") == F.col("full")).alias("extra"))
    single = plan.where(F.size("picks") > 0).select("skey", F.lit(-1).cast("long").alias("block"), F.col("full").alias("c"), F.lit(True).alias("extra"))
    draws = copies.union(single).withColumn("rank", F.row_number().over(Window.partitionBy("skey").orderBy("c", F.col("block") < 0, "block")).cast("long"))
    draws = materialize(draws)
    quota = materialize(split_tree(draws.groupBy("skey").agg(F.count(F.lit(1)).alias("n")), levels, seed))
    ends = quota.withColumn("hi", F.sum("n").over(Window.partitionBy("skey").orderBy("shard")))
    ranks = ends.select("skey", "shard", F.explode(F.sequence(F.col("hi") - F.col("n") + 1, F.col("hi"))).alias("rank"))
    placed = draws.join(ranks, ["skey", "rank"])
    cells = placed.groupBy("skey", "block").agg(F.sort_array(F.collect_list(F.when(~F.col("extra"), F.struct("c", "shard")))).alias("whole"), F.max(F.when(F.col("extra"), F.col("shard"))).alias("part"))
    singles = cells.where("block = -1").select("skey", F.col("part").alias("single"))
    cells = blocks.select("skey", "block").join(cells.where("block >= 0"), ["skey", "block"], "left").join(plan, "skey").join(singles, "skey", "left")
    cells = materialize(cells.select(*[F.col(c).alias(f"{p}{c}") for c in ("skey", "block", "whole", "part", "single", "source_size", "target", "runs", "picks")]))

    rows = docs.withColumns({f"{p}size": size, f"{p}skey": skey, f"{p}u": u})
    rows = rows.withColumn(f"{p}block", F.shiftright(F.col(f"{p}u"), KEY_BITS - bits).cast("long"))
    rows = rows.join(F.broadcast(cells) if n_sources << bits <= BROADCAST_CELLS else cells, [f"{p}skey", f"{p}block"], "left")
    c = {k: F.col(f"{p}{k}") for k in ("whole", "part", "single", "u", "runs", "picks", "size")}
    whole = F.transform(F.coalesce(c["whole"], F.array().cast("array<struct<c:bigint,shard:bigint>>")), lambda x: x["shard"])
    # equal ids are one unit: its size is that of all their rows
    unit = units.select(F.col("skey").alias(f"{p}skey"), F.col("u").alias(f"{p}u"), F.col("size").alias(f"{p}unit"), "n").where("n > 1").drop("n")
    if unit.limit(1).count():
        rows = rows.join(unit, [f"{p}skey", f"{p}u"], "left").withColumn(f"{p}unit", F.coalesce(f"{p}unit", f"{p}size"))
    else:
        rows = rows.withColumn(f"{p}unit", c["size"])
    run = F.exists(c["runs"], lambda r: (c["u"] > r["lo"]) & (c["u"] <= r["hi"]) & (F.col(f"{p}unit") <= r["g"]))
    more = F.when(run, F.array(c["part"])).when(F.array_contains(c["picks"], c["u"]), F.array(c["single"])).otherwise(F.array().cast("array<bigint>"))
    taken = F.when(c["size"] > 0, F.concat(whole, more)).otherwise(F.array().cast("array<bigint>"))
    rows = rows.withColumn(f"{p}shards", taken).drop(*[f"{p}{k}" for k in ("skey", "block", "whole", "part", "single", "runs", "picks", "unit")])
    return rows, p


def mix(docs: DataFrame, seed: int = 17, shard_col: str = "mix_shard", **options) -> DataFrame:
    """The mixture itself: docs' columns and mix_shard, one row per copy, each shard one partition in a local random order."""
    rows, p = mix_plan(docs, seed=seed, **options)
    out = rows.select("*", F.posexplode(F.col(f"{p}shards")).alias(f"{p}copy", f"{p}shard"))
    shard_col = shard_col if shard_col not in docs.columns else f"{p}shard_"
    out = out.repartition(F.col(f"{p}shard")).sortWithinPartitions(f"{p}shard", F.xxhash64(F.lit(seed), F.col(f"{p}u"), F.col(f"{p}copy")))
    return out.select(*docs.columns, F.col(f"{p}shard").alias(shard_col))


def op3_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, p = mix_plan(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    return rows.select("doc_id", F.col(f"{p}size").alias("size"), F.col(f"{p}source_size").alias("source_size"), F.col(f"{p}target").alias("target"), (F.col(f"{p}size") * F.size(F.col(f"{p}shards"))).cast("long").alias("taken"))


def oracle(docs: str = "documents", weights=WEIGHTS, share: float = 1.5, cap: float = 2.0, seed: int = 17) -> str:
    """The same rows in DuckDB: no blocks and no tree, the runs are found on the whole permuted order."""
    runs, prev = [], "k0"
    for i in range(1, SKIPS + 1):
        runs.append(f""", c{i} AS (SELECT skey, max(u) AS hi, max(cum) AS cum FROM (SELECT u.skey, u.u, p.left_words, max(u.size) OVER (PARTITION BY u.skey) AS top, sum(u.size) OVER (PARTITION BY u.skey ORDER BY u.u) AS cum FROM units u JOIN {prev} p USING (skey)
            WHERE u.u > p.cut AND u.size > 0 AND u.size <= p.left_words) WHERE cum <= left_words{f' AND left_words > {PICKS} * top' if i > 1 else ''} GROUP BY skey),
        k{i} AS (SELECT p.* REPLACE (coalesce(c.hi, p.cut) AS cut, p.left_words - coalesce(c.cum, 0) AS left_words, CASE WHEN c.hi IS NULL THEN p.runs ELSE list_append(p.runs, struct_pack(lo := p.cut, hi := c.hi, g := p.left_words)) END AS runs) FROM {prev} p LEFT JOIN c{i} c USING (skey))""")
        prev = f"k{i}"
    picks = [f", p AS (SELECT *, []::BIGINT[] AS picks FROM {prev})"]
    prev = "p"
    for i in range(PICKS + 1):
        last = i == PICKS
        room = "u.size > p.left_words AND u.size < 2 * p.left_words" if last else "u.size > 0 AND u.size <= p.left_words"
        picks.append(f""", best{i} AS (SELECT p.skey, {'min' if last else 'max'}(struct_pack(size := u.size, u := u.u)) AS b FROM units u JOIN {prev} p USING (skey)
          WHERE u.u > p.cut AND {room} AND NOT list_contains(p.picks, u.u) GROUP BY p.skey),
        p{i} AS (SELECT p.* REPLACE (p.left_words - coalesce(b.b.size, 0) AS left_words, CASE WHEN b.b IS NULL THEN p.picks ELSE list_append(p.picks, b.b.u) END AS picks) FROM {prev} p LEFT JOIN best{i} b USING (skey))""")
        prev = f"p{i}"
    ws = ", ".join(f"{float(x)}" for x in weights)
    return f"""
    WITH base AS (SELECT doc_id, source, coalesce('s' || source, 'n') AS skey, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size,
        ('0x' || substr(md5('{seed}:' || coalesce(doc_id::VARCHAR, '')), 1, 15))::BIGINT AS u FROM {docs}),
    units AS (SELECT skey, u, any_value(source) AS source, sum(size)::BIGINT AS size FROM base GROUP BY skey, u),
    s0 AS (SELECT skey, any_value(source) AS source, sum(size)::BIGINT AS source_size FROM units GROUP BY skey),
    s1 AS (SELECT *, list_extract([{ws}], ((row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % {len(weights)} + 1)::INT)::DOUBLE AS w, ({cap} * source_size)::DOUBLE AS most FROM s0),
    s2 AS (SELECT *, most / w AS ratio FROM s1),
    s3 AS (SELECT *, ({share} * sum(source_size) OVER () - coalesce(sum(most) OVER (ORDER BY ratio, skey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum(w) OVER (ORDER BY ratio, skey ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level, row_number() OVER (ORDER BY ratio, skey) AS pos FROM s2),
    lv AS (SELECT min_by(level, pos) AS level FROM s3 WHERE level * w <= most),
    s4 AS (SELECT skey, source_size, CASE WHEN lv.level IS NULL THEN most ELSE least(most, lv.level * w) END AS target FROM s3 CROSS JOIN lv),
    s5 AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END::BIGINT AS full_copies FROM s4),
    s6 AS (SELECT *, target - full_copies * source_size AS rest FROM s5),
    k0 AS (SELECT skey, source_size, target, full_copies, -1::BIGINT AS cut, rest AS left_words, []::STRUCT(lo BIGINT, hi BIGINT, g DOUBLE)[] AS runs FROM s6)
    {''.join(runs)}{''.join(picks)}
    SELECT d.doc_id, d.size, p.source_size, p.target, (d.size * (p.full_copies + CASE WHEN u.size > 0 AND (len(list_filter(p.runs, lambda r: u.u > r.lo AND u.u <= r.hi AND u.size <= r.g)) > 0 OR list_contains(p.picks, u.u)) THEN 1 ELSE 0 END))::BIGINT AS taken
    FROM base d JOIN {prev} p USING (skey) JOIN units u USING (skey, u)"""
