"""The test bed: logical databases over the given tables and derived noisy tables with known truth, as pure expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hopjoin.functions import noise
from hopjoin.plans.config import TableRef

#: Fixed values of the fixtures.
PLACES = "Alder Bay,Birch Hollow,Cedar Point,Dover Flats,Elm Ridge,Falcon Heights,Garnet Falls,Harbor Glen,Iron Mesa,Juniper Creek,Kestrel Moor,Laurel Springs,Maple Crossing,North Haven,Oak Summit,Pine Meadow,Quarry Hill,River Bend,Stone Arch,Tamarack Lake,Upland Park,Vista Grove,Willow Shore,Yarrow Field,Zephyr Cove".split(",")
GIVEN = "Ada Bruno Clara Dmitri Elena Farid Greta Hugo Irene Jonas Katya Liam Marta Nils Olga Pavel Quinn Rosa Stefan Tessa".split()
FAMILY = "Abbott Barros Castell Devlin Eriksen Fontaine Gallagher Hartmann Ibarra Jansson Kowalski Lindqvist Moreau Novak Okafor Petrov Quintero Rossi Sandoval Takeda Ulrich Varga Whitlock Xanthos Yilmaz".split()
MIDDLE = "Ames Boyd Crane Dunn Ellis Ford Grant Hale Irwin Judd Knox Lowe".split()
MISSPELT = {"anvil": "anvyl", "bolt": "boult", "gear": "geer", "gizmo": "gismo", "plate": "playte", "ring": "rynge", "rod": "rodd", "widget": "widjit"}

DATABASES = {
    "trade_db": ("customer", "orders", "lineitem", "supplier", "nation", "region"),
    "goods_db": ("part",),
    "activity_db": ("events", "conversations"),
    "corpus_db": ("documents", "labels", "benchmark", "pages", "embeddings"),
}
#: source table and column, target table and column; all in one database each
FOREIGN_KEYS = (
    ("trade_db", "lineitem", "l_orderkey", "orders", "o_orderkey"),
    ("trade_db", "lineitem", "l_suppkey", "supplier", "s_suppkey"),
    ("trade_db", "orders", "o_custkey", "customer", "c_custkey"),
    ("trade_db", "customer", "c_nationkey", "nation", "n_nationkey"),
    ("trade_db", "supplier", "s_nationkey", "nation", "n_nationkey"),
    ("trade_db", "nation", "n_regionkey", "region", "r_regionkey"),
    ("corpus_db", "labels", "doc_id", "documents", "doc_id"),
)


_I, _S, _F, _T = "integral", "string", "fractional", "temporal"
#: The columns of the given tables and their type families.
COLUMNS = {
    "region": (("r_regionkey", _I), ("r_name", _S)),
    "nation": (("n_nationkey", _I), ("n_name", _S), ("n_regionkey", _I)),
    "customer": (("c_custkey", _I), ("c_name", _S), ("c_nationkey", _I), ("c_acctbal", _F), ("c_mktsegment", _S)),
    "supplier": (("s_suppkey", _I), ("s_name", _S), ("s_nationkey", _I), ("s_acctbal", _F)),
    "part": (("p_partkey", _I), ("p_name", _S), ("p_brand", _S), ("p_type", _S), ("p_size", _I), ("p_retailprice", _F)),
    "orders": (("o_orderkey", _I), ("o_custkey", _I), ("o_orderstatus", _S), ("o_totalprice", _F), ("o_orderdate", _T), ("o_orderpriority", _S)),
    "lineitem": (
        ("l_orderkey", _I), ("l_partkey", _I), ("l_suppkey", _I), ("l_linenumber", _I), ("l_quantity", _F), ("l_extendedprice", _F),
        ("l_discount", _F), ("l_tax", _F), ("l_returnflag", _S), ("l_linestatus", _S), ("l_shipdate", _T),
    ),
    "events": (("event_id", _I), ("ts", _T), ("user_id", _I), ("event_type", _S), ("value", _F), ("props", _S)),
    "documents": (("doc_id", _I), ("text", _S), ("lang", _S), ("source", _S), ("n_chars", _I)),
    "labels": (("doc_id", _I), ("quality", _I), ("toxic", _I)),
    "benchmark": (("item_id", _I), ("text", _S)),
    "pages": (("page_id", _I), ("url", _S), ("html", _S)),
    "embeddings": (("vec_id", _I), ("embedding", "other"), ("label", _I)),
    "conversations": (("conv_id", _I), ("turn", _I), ("role", _S), ("text", _S)),
}
#: the stand-ins with names, and the derived tables
DERIVED = {
    "nation": (("n_nationkey", _I), ("place_name", _S), ("n_regionkey", _I)),
    "customer": (("c_custkey", _I), ("person_name", _S), ("c_nationkey", _I), ("c_acctbal", _F), ("c_mktsegment", _S)),
    "part": (("p_partkey", _I), ("part_name", _S), ("p_brand", _S), ("p_type", _S), ("p_size", _I), ("p_retailprice", _F)),
    "place_survey": (("survey_id", _I), ("territory_name", _S), ("satisfaction", _F)),
    "resident_registry": (("citizen_id", _I), ("resident_name", _S), ("household", _I)),
    "part_watchlist": (("watch_id", _I), ("item_name", _S), ("risk", _I)),
}
PUBLIC = ("place_survey", "resident_registry", "part_watchlist")


def load(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """All given tables by name (footers only until an action)."""
    return {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for ts in DATABASES.values() for t in ts}


def _pick(values: list[str], i: Column) -> Column:
    return F.element_at(F.array(*[F.lit(v) for v in values]), i.cast("int") + 1)


def nation_named(nation: DataFrame) -> DataFrame:
    return nation.select("n_nationkey", _pick(PLACES, F.col("n_nationkey")).alias("place_name"), "n_regionkey")


def place_survey(nation: DataFrame) -> DataFrame:
    k, name = F.col("n_nationkey"), F.col("place_name")
    plan = [name, noise.reverse_parts(name), noise.drop_chars(name, k), F.concat(name, F.when(F.floor(k / 4) % 2 == 0, F.lit(" Clinic")).otherwise(F.lit(" Hospital")))]
    return nation_named(nation).where(F.pmod(k, F.lit(6)) != 5).select(k.cast("int").alias("survey_id"), noise.choose(k, plan).alias("territory_name"), (4 + F.pmod(k * 37, F.lit(100)) / 100).alias("satisfaction"))


def person_name(k: Column) -> Column:
    given, family = _pick(GIVEN, F.pmod(k, F.lit(20))), _pick(FAMILY, F.pmod(F.floor(k / 20), F.lit(25)))
    middle = _pick(MIDDLE, F.pmod(F.floor(k / 500), F.lit(12)))
    return F.when(k < 500, F.concat_ws(" ", given, family)).otherwise(F.concat_ws(" ", given, middle, family))


def customer_named(customer: DataFrame) -> DataFrame:
    return customer.select("c_custkey", person_name(F.col("c_custkey")).alias("person_name"), "c_nationkey", "c_acctbal", "c_mktsegment")


def resident_registry(customer: DataFrame) -> DataFrame:
    k, name = F.col("c_custkey"), person_name(F.col("c_custkey"))
    parts = F.split(name, " ")
    family_first = F.concat_ws(" ", F.element_at(parts, -1), F.array_join(F.slice(parts, 1, F.size(parts) - 1), " "))
    plan = [name, family_first, noise.drop_chars(name, k), noise.drop_chars(name, k, 2)]
    return customer.where(F.pmod(k, F.lit(5)) != 4).select(k.alias("citizen_id"), noise.choose(k, plan).alias("resident_name"), F.pmod(k, F.lit(7)).cast("int").alias("household"))


def part_named(part: DataFrame) -> DataFrame:
    return part.withColumnRenamed("p_name", "part_name")


def part_ranks(part: DataFrame) -> DataFrame:
    """(k, p_name): the distinct part names (64 by construction) and their rank, from one small set."""
    names = part.agg(F.array_sort(F.collect_set("p_name")).alias("names"))
    return names.select(F.posexplode("names").alias("k", "p_name"))


def part_watchlist(part: DataFrame) -> DataFrame:
    """One row per distinct part name."""
    named = part_ranks(part)
    k, name = F.col("k"), F.col("p_name")
    plan = [name, noise.reverse_parts(name), noise.drop_chars(name, k), F.concat(name, F.lit(" Item")), noise.synonyms(name, MISSPELT)]
    return named.select(k.cast("int").alias("watch_id"), noise.choose(k, plan).alias("item_name"), F.pmod(k, F.lit(3)).cast("int").alias("risk"))


def nation_adversarial(nation: DataFrame) -> DataFrame:
    k, name = F.col("n_nationkey"), F.col("n_name")
    plan = [name, F.concat(name, F.lit(" Territory")), noise.drop_chars(name, k, 1, 2, 5), F.concat(F.lit("Greater "), name)]
    return nation.select(k.alias("n_nationkey"), noise.choose(k, plan).alias("label"))


def test_bed(spark: SparkSession, sf_dir: str, given: bool = True) -> list[TableRef]:
    """The tables of the experiment: given ones (or the named stand-ins only) and the derived public database."""
    t = load(spark, sf_dir)
    refs = []
    for db, names in DATABASES.items():
        for name in names:
            df = {"nation": nation_named, "customer": customer_named, "part": part_named}.get(name, lambda x: x)(t[name])
            refs.append(TableRef(db, name, df))
    if not given:
        refs = [r for r in refs if r.table in ("nation", "customer", "part", "supplier")]
    return refs + [TableRef("public_db", "place_survey", place_survey(t["nation"])), TableRef("public_db", "resident_registry", resident_registry(t["customer"])), TableRef("public_db", "part_watchlist", part_watchlist(t["part"]))]


def fk_manifest(spark: SparkSession) -> DataFrame:
    rows = [(db, a, [x], b, [y]) for db, a, x, b, y in FOREIGN_KEYS]
    return spark.createDataFrame(rows, "db string, src_table string, src_columns array<string>, dst_table string, dst_columns array<string>")
