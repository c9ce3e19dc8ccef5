"""Worked cases and properties of the curation methods."""

from __future__ import annotations

import math
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from textquarry import plans, registry
from textquarry.functions import text as T
from textquarry.operators import align, clean, dedup, lm, signals
from textquarry.operators import templating as tp

plans.load()
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
FAST = ["q_signals", "q_flag_nsfw", "q_clean_document", "q_token_cube", "q_html_extract", "q_site_verdicts", "q_dedup_exact", "q_ppl_report", "q_tpl_roundtrip", "q_rom_replace", "q_pdf_documents", "q_box_suppress", "q_conv_valid", "q_lid_ensemble", "q_join_asof", "q_stream_tumbling"]


def _plain(x):
    return repr(round(x, 6)) if isinstance(x, float) else repr(x)


@pytest.mark.parametrize("name", FAST)
def test_query_equals_oracle(spark, sf_dir, name):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    df = registry.QUERIES[name](spark, sf_dir)
    out = c.sql(registry.ORACLES[name])
    assert sorted(df.columns) == sorted(out.columns)
    want = sorted(tuple(map(_plain, r)) for r in c.sql(f"select {', '.join(sorted(out.columns))} from out").fetchall())
    got = sorted(tuple(map(_plain, r)) for r in df.select(*sorted(df.columns)).collect())
    assert got == want


def test_cleaning_is_idempotent_and_never_longer(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for f in (clean.keep_terminated, clean.drop_symbol_chunks, clean.drop_repeated_chunks, clean.drop_short_chunks):
        once = docs.select(F.length("text").alias("n"), f(F.col("text")).alias("a"))
        twice = once.select("n", "a", f(F.col("a")).alias("b"))
        assert twice.filter("a <> b or length(a) > n").count() == 0


def test_repetition_forms_agree(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").filter("n_chars < 3000")
    cols = docs.select(signals.char_repetition(F.col("text")).alias("c"), F.pandas_udf(signals.repetition_scores, "char_rep double, word_rep double")("text").alias("r"))
    assert cols.filter("abs(c - r.char_rep) > 1e-9").count() == 0


def test_templates_are_lossless(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    back = F.array_join(F.transform(tp.segments(F.col("text")), lambda s: s["text"]), "")
    assert docs.filter(back != F.col("text")).count() == 0
    pieces = F.array_join(tp.word_pieces(F.col("text")), "")
    assert docs.filter(pieces != F.col("text")).count() == 0


def test_kneser_ney_sums_to_one(spark):
    docs = spark.createDataFrame([(0, "en", "a b a. b a c."), (1, "en", "a b c.")], "doc_id long, lang string, text string")
    model = lm.kneser_ney(lm.sequences(docs), 2)
    vocab = [r["g"] for r in model.probs[0].select("g").distinct().collect()] + ["<unk>"]
    probe = spark.createDataFrame([(i, "en", ["a", w]) for i, w in enumerate(vocab)], "doc_id long, lang string, s array<string>")
    total = sum(1 / r["ppl"] for r in lm.perplexity(probe, model).collect())
    assert math.isclose(total, 1.0, abs_tol=1e-9)


def test_bands_and_components(spark):
    b, r = dedup.choose_bands()
    assert b * r <= 128 and 1 - (1 - 0.7**r) ** b > 0.9
    edges = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 101)], "src long, dst long")
    roots = {x["node"]: x["root"] for x in dedup.components(edges).collect()}
    assert all(roots[i] == 0 for i in range(61)) and roots[101] == 100


def test_mtld_worked_examples():
    assert align.mtld_score(["a"] * 10) == 2.0
    words = [f"w{i}" for i in range(50)]
    assert align.mtld_score(words) == 50.0
    assert align.mtld_score(words[::-1]) == align.mtld_score(words)


def test_ngrams_and_repeated_share(spark):
    df = spark.createDataFrame([(["a", "b", "c"],), (["a"],), ([],)], "w array<string>")
    assert [r[0] for r in df.select(T.ngrams(F.col("w"), 2)).collect()] == [["a b", "b c"], ["a"], []]
    df = spark.createDataFrame([([1, 1, 2, 3, 3, 3],), ([],)], "w array<long>")
    assert [r[0] for r in df.select(T.repeated_share(F.col("w"), 3)).collect()] == [0.5, 0.0]


def test_entry_point_registers_everything():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries()) and len(registry.QUERIES) > 120
    assert np.all([callable(f) for f in e.queries().values()]) and os.path.exists(e.__file__)
