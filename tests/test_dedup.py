"""Fuzzy deduplication against all pairs, on groups of many variants, chains, copies and texts without words."""

from __future__ import annotations

import random

from pyspark.sql import functions as F

from textquarry.operators import dedup, vectors


def variants(seed: int = 3) -> list[str]:
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(5))
    out = []
    for group, size in ((0, 90), (1, 4), (2, 1)):
        base = [word() for _ in range(120)]
        for k in range(size):
            text = list(base)
            for _ in range(k % 5):
                text[rng.randrange(120)] = word()
            out.append(" ".join(text))
    chain = [word() for _ in range(100)]
    for _ in range(8):  # each like the one before, the ends unlike
        out.append(" ".join(chain))
        for i in rng.sample(range(100), 2):
            chain[i] = word()
    footer = " ".join(word() for _ in range(40))
    out += [" ".join(word() for _ in range(60)) + " " + footer for _ in range(40)]
    return out + out[:3] + ["", None, "one two", "one two", "...", "one"]


def test_clusters_equal_all_pairs(spark):
    rows = [(i, t, "en" if i % 50 else "de") for i, t in enumerate(variants())]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    exact = dedup.exact_jaccard_pairs(docs.filter("text is not null"))
    want = {(r["node"], r["root"]) for r in dedup.components(exact).collect()}
    assert {(r["node"], r["root"]) for r in dedup.clusters(docs).collect()} == want
    kept, removed = dedup.fuzzy_dedup(docs)
    assert kept.count() == len(rows) - sum(a != b for a, b in want) and removed.count() == sum(a != b for a, b in want)
    pairs = {(r["src"], r["dst"]) for r in exact.filter("jaccard < 1").collect()}
    found = {(r["src"], r["dst"]) for r in dedup.verified_pairs(docs).collect()}
    reps = {r["rep"] for r in dedup.Buckets(docs, "t").classes.collect()}
    assert found == {p for p in pairs if set(p) <= reps}


def test_against_base(spark):
    texts = variants()
    rows = [(i, t, "en") for i, t in enumerate(texts)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    base, new = docs.filter("doc_id % 3 = 0"), docs.filter("doc_id % 3 <> 0")
    exact = dedup.exact_jaccard_pairs(docs.filter("text is not null")).select("src", "dst").collect()
    want = {y for r in exact for x, y in ((r["src"], r["dst"]), (r["dst"], r["src"])) if x % 3 == 0 and y % 3}
    assert {r["doc_id"] for r in dedup.dedup_against(new, base).collect()} == want


def test_bands_and_empty_tables(spark):
    bands, rows = dedup.bands_at_recall()
    assert 1 - (1 - 0.7**rows) ** bands >= 0.999 and bands * rows <= dedup.PERMUTATIONS
    empty = spark.createDataFrame([], "doc_id long, text string, lang string")
    assert dedup.clusters(empty).count() == 0 and dedup.verified_pairs(empty).count() == 0


def test_vector_pairs(spark):
    rng = random.Random(5)
    rows = [(i, [rng.gauss(0, 1) for _ in range(6)]) for i in range(300)] + [(300, None), (301, [0.0] * 6)]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    cos = lambda a, b: sum(x * y for x, y in zip(a, b, strict=True)) / (sum(x * x for x in a) * sum(x * x for x in b)) ** 0.5
    want = {(i, j) for i, a in rows[:300] if i % 20 == 0 for j, b in rows[:300] if i != j and cos(a, b) >= 0.6}
    got = {(r["src"], r["dst"]) for r in vectors.vector_pairs(v, v.filter(F.col("vec_id") % 20 == 0), 0.6, block=64).collect()}
    assert got == want and want


def test_pairs_without_bands_equal_all_pairs(spark):
    """the prefix filter loses no link between different texts, copies are members of their representative."""
    rows = [(i, t, "en" if i % 50 else "de") for i, t in enumerate(variants())] + [(9000, "one two", None), (9001, "one two", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3)
    exact = dedup.exact_jaccard_pairs(docs.filter("text is not null"))
    x = dedup.Exact(docs)
    copies = dict((r["node"], r["rep"]) for r in x.copies().collect())
    got = {(r["src"], r["dst"]): r["jaccard"] for r in x.links.collect()}
    assert got == {(r["src"], r["dst"]): r["jaccard"] for r in exact.collect() if copies[r["src"]] == r["src"] and copies[r["dst"]] == r["dst"]} and len(got) > 1000
    assert {(r["node"], r["root"]) for r in x.clusters().collect()} == {(r["node"], r["root"]) for r in dedup.components(exact).collect()}
    assert dedup.Exact(docs.limit(0)).clusters().count() == 0


def test_pairs_without_bands_do_not_join_posting_lists(spark, sf_dir, monkeypatch):
    from textquarry import plans, registry

    plans.load()

    def refuse(*_, **__):
        raise AssertionError("all pairs of posting lists")

    monkeypatch.setattr(dedup, "exact_jaccard_pairs", refuse)
    assert all(registry.QUERIES[q](spark, sf_dir).count() for q in ("q_jaccard_pairs", "q_dedup_brute", "q_lsh_quality"))
