"""The findings of round 3, one test each."""

from __future__ import annotations

from collections import defaultdict
from itertools import combinations

import numpy as np
import pytest

from textquarry import plans, registry
from textquarry.llm import topk
from textquarry.operators import dedup

from .test_dedup import variants


@pytest.mark.parametrize("tile", [1024, 7])
def test_f2_candidates_are_all_pairs_of_the_buckets(spark, tmp_path, monkeypatch, tile):
    """Buckets of any size propose all their pairs, and nothing else does; the report counts them."""
    plans.load()
    monkeypatch.setattr(dedup, "TILE", tile, raising=False)
    rows = [(i, t, "en" if i % 50 else "de") for i, t in enumerate(variants())] + [(9000, "one two", None), (9001, "one two", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3)
    buckets, classes = defaultdict(set), {}
    for r in dedup.signatures(docs, 5, *dedup.bands_at_recall()).filter("lang is not null").orderBy("doc_id").collect():
        classes.setdefault((r["lang"], r["a"], r["b"], r["n"]), (r["doc_id"], r["bands"]))
    for (lang, *_), (rep, bands) in classes.items():
        for band, h in enumerate(bands):
            buckets[lang, band, h].add(rep)
    want = sorted({(lang, *pair) for (lang, _, _), members in buckets.items() for pair in combinations(sorted(members), 2)})
    assert max(map(len, buckets.values())) > dedup.SMALL
    assert sorted(tuple(r) for r in dedup.band_pairs(docs).select("lang", "src", "dst").collect()) == want
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    row = registry.QUERIES["q_lsh_quality"](spark, str(tmp_path)).first()
    near = {(r["src"], r["dst"]) for r in dedup.exact_jaccard_pairs(docs.filter("text is not null")).collect()}
    near = {p for p in near if set(p) <= {rep for rep, _ in classes.values()}}
    found = {p[1:] for p in want} & near
    every = sum(1 for _ in combinations(classes, 2))
    assert (row["pairs"], row["candidates"], row["found"]) == (len(near), len(want), len(found))
    assert (row["recall"], row["precision"], row["reduction"]) == pytest.approx((len(found) / len(near), len(found) / len(want), 1 - len(want) / every))


def test_f2_empty_table_has_no_candidates(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, lang string")
    assert dedup.band_pairs(empty).count() == 0


@pytest.mark.parametrize("wide", [16, 0])
@pytest.mark.parametrize("size", [1, 3000])
def test_f1_queries_are_searched_together(monkeypatch, wide, size):
    """A block answers many queries at once as all products do, with runs or rows bounded, in short floats and long ones; clusters far from a query are not evaluated."""
    monkeypatch.setattr(topk, "WIDE", wide, raising=False)
    monkeypatch.setattr(topk, "FRESH", 50, raising=False)
    rng = np.random.default_rng(7)
    x = np.floor(size * (rng.normal(0, 64, (9, 12))[rng.integers(0, 9, 2000)] + rng.normal(0, 2, (2000, 12))))
    x[100:160] = x[100]
    ids = rng.permutation(5000)[:2000].astype(np.int64)
    square = (x**2).sum(1)
    top = float(square.max())
    pivots = topk.choose_pivots(x, topk.PIVOTS)
    pivot_last = np.sqrt(np.maximum(top - (pivots**2).sum(1), 0))
    table = topk._distances(x, np.sqrt(np.maximum(top - square, 0)), pivots, pivot_last).astype(np.float32)
    kind = np.float32 if top**2 < 2.0**48 else np.float64
    assert (kind is np.float32) == (size == 1)
    block, asked = topk._Block(ids, x.astype(kind), table, top), np.arange(0, 2000, 9)
    q = x[asked]
    score = q @ x.T
    score[np.arange(len(asked)), asked] = -np.inf
    floor = np.where(np.arange(len(asked)) % 2 == 0, -np.inf, np.sort(score, axis=1)[:, -30])
    floor[5] = np.inf
    who, found, scores, done = block.search(ids[asked], q, topk._distances(q, np.zeros(len(q)), pivots, pivot_last), floor, 20)
    for n in range(len(asked)):
        want = [] if n == 5 else [(score[n, j], ids[j]) for j in np.lexsort((ids, -score[n]))[:20]]
        assert list(zip(scores[who == n], found[who == n], strict=True)) == want
    assert 0 < done.sum() < 0.5 * len(asked) * len(ids) and done[5] == 0


def test_f1_long_vectors_lose_no_row_to_rounding(spark):
    """Bounds leave room for the rounding of long distances: vectors of great length whose scores lie close together."""
    rng = np.random.default_rng(11)
    centres = rng.normal(0, 3000, (6, 24))
    x = centres[rng.integers(0, 6, 4000)] + rng.normal(0, 0.05, (4000, 24))
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {(r["query_id"], r["rank"]): (r["vec_id"], r["score"]) for r in topk.top_k(v, v.filter("vec_id % 100 = 0"), k=20).collect()}
    whole = np.floor(64 * x)
    for i in range(0, 4000, 100):
        score = whole @ whole[i]
        score[i] = -np.inf
        order = np.lexsort((np.arange(4000), -score))[:20]
        assert [got[i, n + 1] for n in range(20)] == [(j, int(score[j])) for j in order]
