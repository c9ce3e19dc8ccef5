"""Plain versions of the operators that SQL cannot express, and awkward tables for all of them."""

from __future__ import annotations

import hashlib
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from textquarry.llm import bpe, jaccard, linededup, ordermin, packing, pii, quality, secrets, topk, toxicity
from textquarry.llm._text import grams, mix, token_hashes

KEY = "password=Abcdef123456"
LINE = "this shared line is long enough to be counted as one"


def awkward_rows() -> list[tuple]:
    texts = [None, "", " ", "\n\n", "a", "a", "ÀÉ ß \U0001f600", "word " * 4000, "x" * 6000, f"own {KEY} end", *[f"d{i}\n{LINE}" for i in range(6)]]
    rows = [(i, t, "en", f"s{i % 3}", len(t or "")) for i, t in enumerate(texts)]
    # Repeated rows, one id with two texts, a null id, nulls everywhere.
    return rows + [rows[4], (4, "another text", "en", "s1", 12), (None, "text without id", None, None, None), (None, None, None, None, None)]


CLASHES = ("live", "_live", "_th", "_doc", "_lost", "_loser", "_gone", "n_lines", "n_dropped", "a", "b", "keeper", "bands", "rep", "score", "Spans", "row")


def awkward(spark, rows=None):
    docs = spark.createDataFrame(awkward_rows() if rows is None else rows, "doc_id long, text string, lang string, source string, n_chars long")
    return docs.select("*", *(F.lit(f"own {c}").alias(c) for c in CLASHES))


def labels(spark, rows=((4, 1, 0), (4, 0, 1), (7, 0, 1), (9, 1, 0), (None, 1, 1), (10, None, None))):
    return spark.createDataFrame(list(rows), "doc_id long, quality int, toxic int")


def vectors(spark, rows):
    return spark.createDataFrame(rows, "vec_id long, embedding array<float>, v string, id string, d string")


@pytest.mark.parametrize("empty", [False, True])
def test_awkward_tables(spark, empty):
    docs, lab = awkward(spark, [] if empty else None), labels(spark, [] if empty else ((4, 1, 0), (4, 0, 1), (7, 0, 1), (9, 1, 0), (None, 1, 1), (10, None, None)))
    n = 0 if empty else len(awkward_rows())
    ranks = {bytes([b]): b for b in range(256)}
    assert pii.pii_digest(docs).count() == n
    assert jaccard.jaccard_join(docs)[0].count() == n
    assert quality.quality_scores(docs, lab).filter("score between 0 and 1").count() == n
    assert secrets.secret_digest(docs).count() == n
    assert toxicity.toxicity_scores(docs, lab).filter("score between 0 and 1").count() == n
    assert linededup.line_digest(docs).count() == n
    assert bpe.code_digest(docs, ranks, r"\S+|\s+").count() == n
    assert ordermin.fingerprint_edits(docs, range_bytes=2000).count() == n
    assert packing.pack(docs).filter("start = 0").count() == n
    rows = [] if empty else [(1, [1.0, 0.5], "x", "y", "z"), (1, [0.5, 0.5], "x", "y", "z"), (2, None, "x", "y", "z"), (3, [1.0, None], "x", "y", "z"), (4, [float("nan"), 1.0], "x", "y", "z"), (None, [1.0, 1.0], "x", "y", "z"), (5, [1.0], "x", "y", "z"), (6, [0.0, 0.0], "x", "y", "z"), (7, [1.0, 0.5], "x", "y", "z")]
    v = vectors(spark, rows)
    assert topk.top_k(v, v, k=5).count() == (0 if empty else 6)


@pytest.mark.parametrize("stage", [s for s, _ in corpus_pipeline.STAGES[:-1]])
def test_stages_keep_columns_of_any_name(spark, tmp_path, stage):
    docs = awkward(spark)
    labels(spark).write.parquet(f"{tmp_path}/labels.parquet")
    out = dict(corpus_pipeline.STAGES)[stage](spark, docs, str(tmp_path))
    assert out.columns == docs.columns
    for r in out.collect():
        assert all(r[c] == f"own {c}" for c in CLASHES)
    empty = dict(corpus_pipeline.STAGES)[stage](spark, awkward(spark, []), str(tmp_path))
    assert empty.columns == docs.columns and empty.count() == 0


def test_secrets_of_many_matches_and_no_values_in_tables(spark, monkeypatch):
    text = " ".join(f"token=Value{i:05d}Zz" for i in range(1300))
    docs = spark.createDataFrame([(1, text, "s"), (2, "token=Value00001Zz", "t")], "doc_id long, text string, source string")
    want = [(m.start(), m.end()) for m in re.finditer(r"token=Value\d{5}Zz", text)]
    rows = {r["doc_id"]: r for r in secrets.secret_scan(docs).collect()}
    assert [(s["start"], s["end"]) for s in rows[1]["plain"]] == want
    assert "value" not in rows[1]["plain"][0].asDict() and secrets.redact_live(docs).filter("text like '%Value%'").count() == 0


# --- Order MinHash -------------------------------------------------------------------------------------------------


def plain_tokens(text: str) -> list[bytes]:
    return re.findall(rb"[A-Za-z0-9_\x80-\xff]+|[^\sA-Za-z0-9_\x80-\xff]", text.encode())


def plain_fingerprint(text: str) -> list[int]:
    words = plain_tokens(text)
    if not words:
        return [0] * ordermin.SKETCHES
    hashes = np.concatenate([token_hashes(np.frombuffer(w, np.uint8), np.array([0]), np.array([len(w)]), fold=False) for w in words])
    values, _ = grams(hashes, np.array([0, len(hashes)]), ordermin.K)
    seen: dict[int, int] = {}
    numbered = []
    for v in values.tolist():
        numbered.append(int(mix(np.array([v], np.uint64) ^ mix(np.array([seen.get(v, 0)], np.uint64) * np.uint64(0x9E3779B1)))[0]))
        seen[v] = seen.get(v, 0) + 1
    factor = (mix(np.arange(7001, 7001 + ordermin.SKETCHES, dtype=np.uint64)) | np.uint64(1)).tolist()
    return [numbered, factor]


def plain_sketches(text: str, bits: int) -> list[int]:
    found = plain_fingerprint(text)
    if len(found) != 2:
        return found
    numbered, factor = found
    low, out = (1 << bits) - 1, []
    for f in factor:
        order = []
        for place, v in enumerate(numbered):
            h = (v * f) & (2**64 - 1)
            order.append((((h ^ (h >> 32)) & ~low & (2**64 - 1)) | place, place))
        chosen = sorted(p for _, p in sorted(order)[: ordermin.TUPLE])
        chosen = [None] * (ordermin.TUPLE - len(chosen)) + chosen
        total = np.zeros(1, np.uint64)
        for t, place in enumerate(chosen):
            total = mix(total * np.uint64(31) + np.uint64(0 if place is None else numbered[place]) + np.uint64(t + 1))
        out.append(int(total[0]))
    return out


def test_order_minhash_equals_plain(spark):
    rng = random.Random(3)
    texts = ["", "one", "a b", "a b a b a b a b", "Wörter, und: Zeichen! (so)", *[" ".join(rng.choice(("to", "be", "or", "not", "x,")) for _ in range(rng.randint(1, 60))) for _ in range(20)]]
    for text in texts:
        count = max(1, len(plain_tokens(text)) - ordermin.K + 1)
        bits = max(1, (count - 1).bit_length())
        got = ordermin.fingerprints(pa.array([text]))[0].tolist()
        assert got == plain_sketches(text, bits), text
    docs = spark.createDataFrame([(i * 3, t) for i, t in enumerate(texts)], "doc_id long, text string")
    rows = {r["doc_id"]: r for r in ordermin.fingerprint_edits(docs, range_bytes=200).collect()}
    ids = sorted(rows, reverse=True)
    like = lambda a, b: sum(a[k : k + 16] == b[k : k + 16] for k in range(0, len(a), 16)) / ordermin.SKETCHES
    for k, i in enumerate(ids):
        text, after = texts[i // 3], texts[ids[(k + 1) % len(ids)] // 3]
        edited = text[: len(text) - len(text) // 2] + after[: len(text) // 2]
        assert rows[i]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert rows[i]["near_next"] == like(rows[i]["fingerprint"], rows[ids[(k + 1) % len(ids)]]["fingerprint"])
        assert rows[i]["near_edited"] == like(rows[i]["fingerprint"], rows[i]["edited_fingerprint"])


# --- packing ---------------------------------------------------------------------------------------------------------


def plain_best_fit(lengths: list[int], openable: tuple[int, ...]) -> list[int]:
    bins: list[list[int]] = []  # room, size
    for need in lengths:
        fits = [b for b in bins if b[0] >= need]
        if fits:
            min(fits, key=lambda b: b[0])[0] -= need
            continue
        held = sum(b[1] - b[0] for b in bins) / max(1, sum(b[1] for b in bins)) if len(bins) > 32 else 0.95
        size = min([c for c in openable if c >= need] or [packing.CAPACITIES[-1]], key=lambda c: (packing.cost(c) / max(need, held * c), c))
        bins.append([size - need, size])
    return sorted(min(c for c in packing.CAPACITIES if c >= b[1] - b[0]) for b in bins)


def test_packing_equals_plain():
    rng = random.Random(9)
    for _ in range(5):
        lengths = sorted((rng.choice((rng.randint(1, 300), rng.randint(1, 4096))) for _ in range(400)), reverse=True)
        plans = [plain_best_fit(lengths, packing.CAPACITIES[k:]) for k in range(len(packing.CAPACITIES))]
        assert [sorted(packing.best_fit(lengths, packing.CAPACITIES[k:])[1]) for k in range(len(packing.CAPACITIES))] == plans
        assert sum(map(packing.cost, packing.pack_group(lengths)[1])) == min(sum(map(packing.cost, p)) for p in plans)


# --- quality ---------------------------------------------------------------------------------------------------------


def test_quality_equals_numpy(spark, sf_dir):
    docs, lab = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    space = corpus_pipeline.Workspace(spark, "test")
    sample = space.write(quality.sample_of(quality.statistics_table(docs), lab.withColumnRenamed("quality", "y"), 3, 1))
    model = quality.fit(sample)
    rows = sample.collect()
    x, y, check = np.array([r["x"] for r in rows], np.float64), np.array([r["y"] for r in rows], float), np.array([r["calibrate"] for r in rows])
    a, b = x[~check], y[~check]
    plain = quality.Model()
    plain.mean, plain.scale = a.mean(0), np.sqrt(np.maximum(a.var(0), 1e-8))
    z, w = plain.lift(a), np.where(b == 1, len(b) / (2 * b.sum()), len(b) / (2 * (len(b) - b.sum())))
    penalty = np.eye(z.shape[1]) * quality.RIDGE
    penalty[0, 0] = 1e-6
    root = np.sqrt(w)[:, None]
    plain.weights = np.linalg.solve((z * root).T @ (z * root) + penalty, z.T @ (w * (2 * b - 1)))
    assert np.allclose(model.raw(x), plain.raw(x), atol=1e-4)
    value, weight = np.array([3.0, 1, 2, 2, 5, 4, 6]), np.array([1.0, 2, 1, 3, 1, 1, 2])
    mean = lambda i, j: np.average(value[i : j + 1], weights=weight[i : j + 1])
    least = [max(min(mean(i, j) for j in range(k, len(value))) for i in range(k + 1)) for k in range(len(value))]
    assert np.allclose(quality.pool_adjacent(value, weight), least)
    assert (np.diff(model.value) >= 0).all() and (np.diff(model.at) > 0).all()


# --- top k -----------------------------------------------------------------------------------------------------------


def test_top_k_eliminates_where_vectors_cluster(spark):
    rng = np.random.default_rng(4)
    centres = rng.normal(0, 1, (12, 16))
    x = centres[rng.integers(0, 12, 3000)] + rng.normal(0, 0.02, (3000, 16))
    rows = [(i, v.tolist()) for i, v in enumerate(x / np.linalg.norm(x, axis=1, keepdims=True))]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    q = v.filter("vec_id % 50 = 0")
    got = {(r["query_id"], r["rank"]): (r["vec_id"], r["score"]) for r in topk.top_k(v, q, k=5, held=700).collect()}
    whole = np.floor(64 * np.array([r[1] for r in rows]))
    for i in range(0, 3000, 50):
        score = whole @ whole[i]
        order = [j for j in np.lexsort((np.arange(3000), -score)) if j != i][:5]
        assert [got[i, k + 1] for k in range(5)] == [(j, int(score[j])) for j in order]
    share = topk.evaluated(v, q, k=5, held=700).agg(F.sum("evaluated") / F.sum("rows")).first()[0]
    assert 0 < share < 0.35


# --- pipeline --------------------------------------------------------------------------------------------------------


def plain_lines(rows: dict[int, str]) -> dict[int, str]:
    key = lambda line: re.sub("[A-Z]", lambda m: m.group(0).lower(), line.strip(" \t\n\x0b\x0c\r"))
    held: dict[str, set[int]] = {}
    for i, t in rows.items():
        for line in (t or "").split("\n"):
            if len(key(line)) >= 40:
                held.setdefault(key(line), set()).add(i)
    gone = {k: max(v) for k, v in held.items() if len(v) >= 5}
    return {i: t if t is None else "\n".join(x for x in t.split("\n") if key(x) not in gone or gone[key(x)] == i) for i, t in rows.items()}


def plain_near(rows: dict[int, str]) -> set[int]:
    """Least ids of the classes of Jaccard 0.8 on five words."""

    def shingles(text: str) -> frozenset:
        w = re.findall(rb"[a-z0-9_\x80-\xff]+", re.sub(rb"[A-Z]", lambda m: m.group(0).lower(), (text or "").encode()))
        return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [("bare", text)])

    sets, index = {i: shingles(t) for i, t in rows.items()}, {}
    for i, s in sets.items():
        for g in s:
            index.setdefault(g, []).append(i)
    root = {i: i for i in rows}

    def find(i: int) -> int:
        while root[i] != i:
            i = root[i]
        return i

    for i, s in sets.items():
        common: dict[int, int] = {}
        for g in s:
            for j in index[g]:
                if j < i:
                    common[j] = common.get(j, 0) + 1
        for j, n in common.items():
            if n >= 0.8 * (len(s) + len(sets[j]) - n):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return {find(i) for i in rows}


def test_pipeline_equals_plain(spark, sf_dir):
    space, docs = corpus_pipeline.Workspace(spark, "test"), spark.read.parquet(f"{sf_dir}/documents.parquet")
    scored = {r["doc_id"]: r["score"] for r in quality.quality_scores(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")).collect()}
    stages = dict(corpus_pipeline.STAGES)
    rows = lambda df: {r["doc_id"]: r["text"] for r in df.collect()}
    good = space.write(stages["quality"](spark, docs, sf_dir))
    assert set(rows(good)) == {i for i, s in scored.items() if s >= 0.5}
    lines = space.write(stages["line_dedup"](spark, good, sf_dir))
    assert rows(lines) == plain_lines(rows(good))
    single = space.write(stages["near_duplicates"](spark, lines, sf_dir))
    assert set(rows(single)) == plain_near(rows(lines))
    clean = space.write(stages["secrets"](spark, single, sf_dir))
    before, after = rows(single), rows(clean)
    live = {r["doc_id"]: r["live"] for r in secrets.secret_scan(single).collect()}
    for i, text in before.items():
        out, at = "", 0
        for s in live[i]:
            if s["start"] >= at:
                out, at = out + text[at : s["end"] - s["size"]] + "<SECRET>", s["end"]
        assert after[i] == (text if text is None else out + text[at:])
    packed = stages["packing"](spark, clean, sf_dir).collect()
    total: dict[int, int] = {}
    for r in packed:
        total[r["doc_id"]] = total.get(r["doc_id"], 0) + r["length"]
    assert total == {i: len((t or "").split()) for i, t in after.items()}


def test_toxicity_scores_equal_plain(spark):
    texts = ["some scum said it", "a friend said it", "scum and scum", "hello friend", "", None] * 20
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    lab = spark.createDataFrame([(i, int("scum" in (t or ""))) for i, t in enumerate(texts)], "doc_id long, toxic int")
    model = toxicity.train(docs, lab)
    table = dict(zip(model.buckets.tolist(), model.weights.tolist(), strict=True))
    got = {r["doc_id"]: r["score"] for r in toxicity.scores(docs, model).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        held = set(toxicity.word_features(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]))[0].tolist()) if raw else set()
        assert abs(got[i] - 1 / (1 + np.exp(-(model.intercept + sum(table.get(b, 0.0) for b in held))))) < 1e-6
        assert (got[i] >= 0.5) == ("scum" in (t or ""))
