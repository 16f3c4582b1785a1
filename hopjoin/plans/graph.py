"""Weighted join graph over tables: edge weights, least-weight paths in three forms, k paths, export."""

from __future__ import annotations

import heapq
import itertools
import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hopjoin.operators.storage import materialize
from hopjoin.plans.config import TableRef


class NoJoinPath(ValueError):
    """The two tables are not connected."""


def edge_weight(s: Column, epsilon: float = 1e-9, base: float = 2.0) -> Column:
    """-log(s + epsilon), never below zero (an overlap of 1 costs nothing)."""
    return F.greatest(F.lit(0.0), -F.log(float(base), s + epsilon))


def weight(s: float, epsilon: float = 1e-9, base: float = 2.0) -> float:
    return max(0.0, -math.log(s + epsilon, base))


def path_overlap(overlaps: Column) -> Column:
    """Product of the hops' overlaps (array<double>)."""
    return F.aggregate(overlaps, F.lit(1.0), lambda a, x: a * x)


def path_weight(weights: Column) -> Column:
    return F.aggregate(weights, F.lit(0.0), lambda a, x: a + x)


def retained(total: Column, base: float = 2.0) -> Column:
    return F.pow(F.lit(base), -total)


@dataclass(frozen=True)
class Hop:
    edge_id: str
    kind: str
    from_node: str
    from_columns: tuple[str, ...]
    to_node: str
    to_columns: tuple[str, ...]
    overlap: float
    weight: float
    forward: bool = True


@dataclass(frozen=True)
class JoinPath:
    source: str
    target: str
    hops: tuple[Hop, ...]
    base: float = 2.0

    @property
    def nodes(self) -> list[str]:
        return [self.source, *[h.to_node for h in self.hops]]

    @property
    def total_weight(self) -> float:
        return sum(h.weight for h in self.hops)

    @property
    def retained(self) -> float:
        return self.base**-self.total_weight

    def key(self):
        """Order of paths: total to six digits, then hops, then edge names - totals that differ by epsilon are ties."""
        return round(self.total_weight, 6), len(self.hops), tuple(h.edge_id for h in self.hops)


PATH_SCHEMA = "source string, target string, hops int, nodes array<string>, edges array<struct<edge_id:string,kind:string,from_node:string,from_columns:array<string>,to_node:string,to_columns:array<string>,overlap:double,weight:double>>, total_weight double, retained double"


def paths_frame(spark: SparkSession, paths: list[JoinPath]) -> DataFrame:
    rows = [(p.source, p.target, len(p.hops), p.nodes, [(h.edge_id, h.kind, h.from_node, list(h.from_columns), h.to_node, list(h.to_columns), h.overlap, h.weight) for h in p.hops], p.total_weight, p.retained) for p in paths]
    return spark.createDataFrame(rows, PATH_SCHEMA)


@dataclass
class JoinGraph:
    """Edges as a DataFrame (edge_id, kind, left_node, left_columns, right_node, right_columns, ..., overlap, weight) and the tables behind the nodes."""

    edges: DataFrame
    tables: dict[str, TableRef] = field(default_factory=dict)
    base: float = 2.0
    max_driver_edges: int = 1_000_000
    found: object = None
    _hops: list[Hop] | None = None

    def hops(self, kinds=("fk", "fuzzy")) -> list[Hop]:
        """Both directions of every edge, on the driver: one row per joinable column pair, guarded by max_driver_edges."""
        if self._hops is None:
            rows = self.edges.select("edge_id", "kind", "left_node", "left_columns", "right_node", "right_columns", "overlap", "weight").limit(self.max_driver_edges + 1).collect()
            if len(rows) > self.max_driver_edges:
                raise ValueError("too many edges for the driver: use all_pairs")
            self._hops = [h for r in rows for h in (Hop(r.edge_id, r.kind, r.left_node, tuple(r.left_columns), r.right_node, tuple(r.right_columns), r.overlap, r.weight), Hop(r.edge_id, r.kind, r.right_node, tuple(r.right_columns), r.left_node, tuple(r.left_columns), r.overlap, r.weight, False))]
        return [h for h in self._hops if h.kind in kinds]

    def matches_of(self, hop: Hop, cfg) -> DataFrame | None:
        """(x, y, sim) that validation found for a fuzzy hop, in the hop's direction; None for a graph read from elsewhere."""
        return self.found.of(hop.edge_id, hop.forward, cfg.assignment, cfg.min_score) if self.found is not None else None


def build(fk: DataFrame, fuzzy: DataFrame | None, tables: list[TableRef] = (), epsilon: float = 1e-9, base: float = 2.0) -> JoinGraph:
    """Union of declared and fuzzy edges (with overlap), weighted."""
    edges = fk if fuzzy is None else fk.unionByName(fuzzy, allowMissingColumns=True)
    return JoinGraph(edges.withColumn("weight", edge_weight(F.col("overlap"), epsilon, base)), {t.node: t for t in tables}, base)


def _search(hops: list[Hop], s: str, t: str, base: float, max_hops: int | None, unit: bool = False, banned_nodes=frozenset(), banned_edges=frozenset()) -> JoinPath | None:
    out: dict[str, list[Hop]] = {}
    for h in hops:
        out.setdefault(h.from_node, []).append(h)
    if s == t:
        return JoinPath(s, t, (), base)
    tick = itertools.count()
    heap = [((0.0, 0, ()), next(tick), s, ())]
    settled: dict = {}
    while heap:
        (cost, n, names), _, node, path = heapq.heappop(heap)
        state = (node, n) if max_hops is not None else node
        if state in settled:
            continue
        settled[state] = True
        if node == t:
            return JoinPath(s, t, path, base)
        if max_hops is not None and n == max_hops:
            continue
        for h in out.get(node, ()):
            if h.to_node in banned_nodes or (h.edge_id, h.from_node) in banned_edges or any(h.to_node == p.from_node for p in path):
                continue
            exact = sum(p.weight for p in path) + h.weight
            heapq.heappush(heap, ((float(n + 1) if unit else round(exact, 6), n + 1, (*names, h.edge_id)), next(tick), h.to_node, (*path, h)))
    return None


def shortest_path(g: JoinGraph, s: str, t: str, kinds=("fk", "fuzzy"), max_hops: int | None = None) -> JoinPath:
    """Least total weight between two tables (label setting over the metadata-sized edge list)."""
    found = _search(g.hops(kinds), s, t, g.base, max_hops)
    if found is None:
        raise NoJoinPath(f"no join path from {s} to {t}")
    return found


def fewest_hops(g: JoinGraph, s: str, t: str, kinds=("fk", "fuzzy")) -> JoinPath:
    """Hop-count path: weights ignored, ties by edge names."""
    found = _search(g.hops(kinds), s, t, g.base, None, unit=True)
    if found is None:
        raise NoJoinPath(f"no join path from {s} to {t}")
    return found


def k_paths(g: JoinGraph, s: str, t: str, k: int, kinds=("fk", "fuzzy")) -> list[JoinPath]:
    """The k best loopless paths, by deviation from those found before."""
    hops = g.hops(kinds)
    first = _search(hops, s, t, g.base, None)
    if first is None:
        raise NoJoinPath(f"no join path from {s} to {t}")
    found, waiting = [first], {}
    while len(found) < k:
        last = found[-1]
        for i in range(len(last.hops)):
            root, spur = last.hops[:i], last.nodes[i]
            banned = {(p.hops[i].edge_id, spur) for p in found if len(p.hops) > i and p.hops[:i] == root}
            tail = _search(hops, spur, t, g.base, None, banned_nodes=frozenset(last.nodes[:i]), banned_edges=frozenset(banned))
            if tail is not None and tail.hops:
                p = JoinPath(s, t, (*root, *tail.hops), g.base)
                waiting[p.key()] = p
        for p in found:
            waiting.pop(p.key(), None)
        if not waiting:
            break
        found.append(waiting.pop(min(waiting)))
    return found


def _all_pairs_local(rows: list, max_hops: int | None, sources: list[str] | None) -> list[tuple[str, str, int, float]]:
    """The same relaxation over a collected edge list."""
    out: dict[str, dict[str, float]] = {}
    for r in rows:
        for u, v in ((r.left_node, r.right_node), (r.right_node, r.left_node)):
            out.setdefault(u, {})[v] = min(r.weight, out.get(u, {}).get(v, math.inf))
    found = []
    for s in sorted(out) if sources is None else [x for x in sources if x in out]:
        best, frontier, hops = {s: (0.0, 0, 0.0)}, [s], 0
        while frontier and (max_hops is None or hops < max_hops):
            hops, step = hops + 1, {}
            for u in frontier:
                for v, w in out[u].items():
                    total = best[u][2] + w
                    step[v] = min(step.get(v, (math.inf,)), (round(total, 6), hops, total))
            frontier = [v for v, x in step.items() if v not in best or x[:2] < best[v][:2]]
            best |= {v: step[v] for v in frontier}
        found += [(s, t, n, total) for t, (_, n, total) in best.items()]
    return found


def all_pairs(edges: DataFrame, max_hops: int | None = None, sources: list[str] | None = None, local_edges: int = 10_000) -> DataFrame:
    """(source, target, hops, total_weight) for all tables, to the fixpoint or max_hops.

    Up to local_edges edges are collected and relaxed on the driver; beyond, frontiers are relaxed as joins, one round per hop,
    each round written out.
    """
    spark = edges.sparkSession
    few = edges.select("left_node", "right_node", "weight").limit(local_edges + 1).collect()
    if len(few) <= local_edges:
        return spark.createDataFrame(_all_pairs_local(few, max_hops, sources), "source string, target string, hops int, total_weight double")
    both = edges.select(F.col("left_node").alias("u"), F.col("right_node").alias("v"), "weight").union(edges.select("right_node", "left_node", "weight"))
    both = materialize(both.groupBy("u", "v").agg(F.min("weight").alias("weight")))
    start = both.select(F.col("u").alias("source")).distinct()
    if sources:
        start = start.where(F.col("source").isin(sources))
    dist = materialize(start.select("source", F.col("source").alias("node"), F.lit(0.0).alias("total"), F.lit(0).alias("hops")))
    best = lambda df: df.groupBy("source", "node").agg(F.min(F.struct(F.round("total", 6).alias("r"), "hops", "total")).alias("b")).select("source", "node", F.col("b.total").alias("total"), F.col("b.hops").alias("hops"))
    frontier = dist
    for _ in range(max_hops) if max_hops is not None else itertools.count():
        step = frontier.join(both, frontier["node"] == both["u"]).select("source", F.col("v").alias("node"), (F.col("total") + F.col("weight")).alias("total"), (F.col("hops") + 1).alias("hops"))
        new = materialize(best(dist.union(step)))
        frontier = new.join(dist.withColumnsRenamed({"total": "t0", "hops": "h0"}), ["source", "node"], "left").where("t0 is null or round(total, 6) < round(t0, 6) or (round(total, 6) = round(t0, 6) and hops < h0)").select("source", "node", "total", "hops")
        dist = new
        if not frontier.limit(1).count():
            break
    return dist.select("source", F.col("node").alias("target"), "hops", F.col("total").alias("total_weight"))


def paths_sql(edges: DataFrame, source: str, max_hops: int = 4) -> DataFrame:
    """Every target's best simple path from a source by a recursive query (small graphs): source, target, hops, nodes, total_weight."""
    spark = edges.sparkSession
    both = edges.select("edge_id", F.col("left_node").alias("u"), F.col("right_node").alias("v"), "weight").union(edges.select("edge_id", "right_node", "left_node", "weight"))
    quoted = source.replace("'", "''")
    return spark.sql(f"""
        WITH RECURSIVE walk(node, hops, nodes, names, total) AS (
            SELECT '{quoted}', 0, array('{quoted}'), '', CAST(0.0 AS DOUBLE)
            UNION ALL
            SELECT e.v, w.hops + 1, array_append(w.nodes, e.v), concat(w.names, '|', e.edge_id), w.total + e.weight
            FROM walk w JOIN {{both}} e ON e.u = w.node WHERE w.hops < {max_hops} AND NOT array_contains(w.nodes, e.v)),
        ranked AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY round(total, 6), hops, names) AS rn FROM walk)
        SELECT '{quoted}' AS source, node AS target, hops, nodes, total AS total_weight FROM ranked WHERE rn = 1""", both=materialize(both))


def to_frames(g: JoinGraph) -> tuple[DataFrame, DataFrame]:
    """Drawing data: nodes coloured by database, edges styled by kind."""
    nodes = g.edges.select(F.explode(F.array("left_node", "right_node")).alias("node")).distinct().withColumn("db", F.split_part("node", F.lit("."), F.lit(1)))
    colour = nodes.withColumn("colour", F.element_at(F.array(*[F.lit(c) for c in ("#4878a8", "#d98b3a", "#5a9e6f", "#b4545a", "#8069a8", "#7f7f7f")]), (F.pmod(F.crc32(F.col("db").cast("binary")), F.lit(6)) + 1).cast("int")))
    edges = g.edges.withColumn("style", F.when(F.col("kind") == "fk", "solid").otherwise("dashed"))
    return colour, edges


def to_dot(g: JoinGraph) -> str:
    nodes, _ = to_frames(g)
    lines = [f'  "{r.node}" [color="{r.colour}"];' for r in nodes.orderBy("node").collect()]
    seen = sorted({(h.edge_id, h.kind, *sorted((h.from_node, h.to_node)), round(h.weight, 3)) for h in g.hops()})
    lines += [f'  "{a}" -- "{b}" [style={"solid" if kind == "fk" else "dashed"}, label="{w}"];' for _, kind, a, b, w in seen]
    return "graph joins {\n" + "\n".join(lines) + "\n}\n"
