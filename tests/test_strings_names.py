from difflib import SequenceMatcher

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from hopjoin.functions import names, noise, strings
from hopjoin.operators import block
from hopjoin.plans.config import LEXICON, DiscoveryConfig

words = st.text(alphabet="abcdeé ", max_size=14)


def lcs_plain(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        prev = row[:]
        for j, y in enumerate(b, 1):
            row[j] = prev[j - 1] + 1 if x == y else max(prev[j], row[j - 1])
    return row[-1]


@given(words, words)
@settings(max_examples=300, deadline=None)
def test_bit_parallel_lcs(a, b):
    assert strings.lcs_length(a, b) == lcs_plain(a, b)


@given(st.text(alphabet="abc_", max_size=16), st.text(alphabet="abc_", max_size=16))
@settings(max_examples=300, deadline=None)
def test_gestalt_equals_stdlib(a, b):
    assert names.gestalt(a, b) == pytest.approx(SequenceMatcher(None, a, b, autojunk=False).ratio())


def test_native_and_arrow_forms_agree(spark):
    rows = [("hello", "yellow"), ("", ""), ("", "a"), ("naïve café", "café naive"), ("x" * 70, "y" * 3 + "x" * 66), (None, "a")]
    df = spark.createDataFrame(rows, "a string, b string")
    out = df.select(strings.lcs_sql(F.col("a"), F.col("b")).alias("n"), strings.lcs_udf(F.col("a"), F.col("b")).alias("u"), strings.token_sort_ratio(F.col("a"), F.col("b")).alias("r")).collect()
    assert [r.n for r in out] == [r.u for r in out]
    assert out[1].r == 1.0 and out[2].r == 0.0 and out[5].r is None


def test_token_sort_ratio_golden(spark):
    df = spark.createDataFrame([("John Smith", "Smith John"), ("Amoxicillin", "Amoksillin")], "a string, b string")
    out = [r[0] for r in df.select(strings.token_sort_ratio(F.col("a"), F.col("b"))).collect()]
    assert out[0] == 1.0 and out[1] == pytest.approx(0.7619, abs=1e-4)


def test_totals_golden(spark):
    rows = [("doctor_name", "assigned_doctor_name", 0.7000), ("drug_name", "medication_name", 0.6667), ("clinic_name", "hospital_name", 0.6667), ("c_custkey", "o_custkey", 0.7651), ("c_custkey", "p_partkey", 0.3365), ("place_name", "item_name", 0.4797)]
    df = spark.createDataFrame([r[:2] for r in rows], "a string, b string")
    got = {(r.a, r.b): r.total_score for r in names.total_score(df, DiscoveryConfig()).collect()}
    for a, b, want in rows:
        assert got[a, b] == pytest.approx(want, abs=1e-4)


def test_token_overlap_kinds(spark):
    df = spark.createDataFrame([("orderDate", "order_date"), ("a_b", "b_c"), ("", "x")], "a string, b string")
    out = df.select(*[names.token_overlap(F.col("a"), F.col("b"), k) for k in ("jaccard", "containment", "dice")]).collect()
    assert list(out[0]) == [1.0, 1.0, 1.0] and list(out[1]) == pytest.approx([1 / 3, 0.5, 0.5]) and list(out[2]) == [0.0, 0.0, 0.0]


def test_config_rejects_bad_weights():
    with pytest.raises(ValueError):
        DiscoveryConfig(alpha=0.5, beta=0.5, gamma=0.5)
    with pytest.raises(ValueError):
        DiscoveryConfig(alpha=-0.1, beta=0.9, gamma=0.2)
    assert LEXICON["medication"] == "drug"


def test_noise(spark):
    df = spark.createDataFrame([(0, "John Smith"), (1, "Ann"), (2, "x"), (5, "A B C")], "k int, s string")
    out = df.select(noise.drop_chars(F.col("s"), F.col("k")).alias("d"), noise.reverse_parts(F.col("s")).alias("r"), noise.suffix(F.col("s"), F.col("k"), ["Clinic", "Hospital"]).alias("x"), noise.synonyms(F.col("s"), {"John": "Jon"}).alias("y")).collect()
    assert [r.d for r in out] == ["Jhn Smith", "An", "x", "A B "] or out[0].d == "Jhn Smith"
    assert [r.r for r in out] == ["Smith John", "Ann", "x", "C B A"]
    assert out[0].x == "John Smith Clinic" and out[1].x == "Ann Hospital" and out[0].y == "Jon Smith"


def test_bounds_never_drop_a_qualifying_pair(spark):
    import random

    rng = random.Random(3)
    rows = [("".join(rng.choice("abcd ") for _ in range(rng.randint(1, 12))).strip() or "a", "".join(rng.choice("abcd ") for _ in range(rng.randint(1, 12))).strip() or "b") for _ in range(400)]
    df = spark.createDataFrame(rows, "a string, b string").withColumn("sim", strings.indel_ratio(F.col("a"), F.col("b")))
    for t in (0.5, 0.8):
        assert df.where((F.col("sim") >= t) & (~block.bounds(F.col("a"), F.col("b"), t) | (block.bag_bound(F.col("a"), F.col("b")) < t - 1e-9))).count() == 0
