"""The stages on planted cases."""

import random
import re

from pyspark.sql import functions as F

import corpus_pipeline
from hopjoin.llm import shingles


def test_near_duplicates_at_the_bar(spark):
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    rows, base = [], []
    for g in range(12):
        w = [word() for _ in range(400)]
        base.append(g * 10)
        for c in range(4):
            v = list(w)
            for i in range(0, 400, 60) if c else ():
                v[i + c] = word()
            rows.append((g * 10 + c, " ".join(v)))
    rows += [(1000 + i, " ".join(word() for _ in range(300))) for i in range(20)]
    got = {r.d: r.root for r in shingles.near_duplicate_groups(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    sets = {d: {tuple(t.split()[i : i + 5]) for i in range(len(t.split()) - 4)} for d, t in rows}
    for d, root in got.items():
        assert root == (d // 10 * 10 if d < 1000 else d)
    assert len(sets[0] & sets[1]) / len(sets[0] | sets[1]) >= 0.8


def groups_by_force(rows, bar=0.8):
    sets = {d: {tuple(t.split()[i : i + 5]) for i in range(len(t.split()) - 4)} for d, t in rows}
    root = {d: d for d in sets}
    near = lambda x, y: len(x & y) * (1 + bar) >= bar * (len(x) + len(y)) - 1e-9
    for a in sets:
        for b in sets:
            if b < a and root[a] != root[b] and near(sets[a], sets[b]):
                low, high = sorted((root[a], root[b]))
                root = {d: low if r == high else r for d, r in root.items()}
    return root


def test_near_duplicates_in_a_hot_bucket(spark):
    rng = random.Random(7)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    passage = [word() for _ in range(280)]
    rows = []
    for g in range(100):
        own = [word() for _ in range(70)]
        rows.append((g, " ".join(passage + own)))
        if g % 2:
            rows.append((1000 + rng.randrange(100) * 1000 + g, " ".join(passage + own[:40] + [word() for _ in range(30)])))
    rng.shuffle(rows)
    got = {r.d: r.root for r in shingles.near_duplicate_groups(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    want = groups_by_force(rows)
    assert len(set(want.values())) == 100 and got == want


def test_long_texts_beside_the_bar(spark):
    rng = random.Random(9)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    rows = []
    for g in range(40):
        w = [word() for _ in range(1504)]  # 1,500 shingles; a run of c new words changes c + 4 of them
        c = (155, 166)[g % 2]  # similarity just over or under 0.8
        rows += [(2 * g, " ".join(w)), (2 * g + 1, " ".join(w[:200] + [word() for _ in range(c)] + w[200 + c :]))]
    got = {r.d: r.root for r in shingles.near_duplicate_groups(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    want = groups_by_force(rows)
    assert len(set(want.values())) == 60 and got == want


def test_stages(spark, sf, odd):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(120)
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language", "near_dups", "benchmark", "secrets", "mix"]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns and 0 < out.count() <= docs.count()
        odd_out = stage(spark, odd, sf)
        assert odd_out.columns == odd.columns
        assert stage(spark, odd.limit(0), sf).count() == 0
        docs = out
    assert "[SECRET]" in corpus_pipeline.secrets(spark, odd, sf).where("doc_id = 10").first().text
    kept = corpus_pipeline.near_dups(spark, odd, sf)
    assert kept.where("doc_id = 1").count() == 1 and kept.where("doc_id is null").count() == 1
    mixed = corpus_pipeline.mix(spark, docs, sf)
    words = lambda df: df.select(F.sum(F.regexp_count("text", F.lit(r"[^\x20\x09-\x0D]+")))).first()[0]
    assert abs(words(mixed) - 1.5 * words(docs)) < 0.02 * words(docs)


def test_secret_texts_hold_no_secret(spark, sf):
    out = corpus_pipeline.secrets(spark, spark.read.parquet(f"{sf}/documents.parquet"), sf).collect()
    assert not any(re.search(r"AKIA[A-Z0-9]{12}|[0-9a-f]{32}", r.text or "") for r in out)
