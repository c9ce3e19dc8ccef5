"""What the reviewer of round 2 found."""

from __future__ import annotations

import time

import pytest
from pyspark.sql import functions as F

from textquarry import config, plans, registry
from textquarry.operators import dedup, lm, lm_buckets
from textquarry.plans import q_lm
from textquarry.streaming import intake


@pytest.fixture(scope="module")
def folders(spark, sf_dir, tmp_path_factory):
    """The documents as a folder of three files, as large tables come."""
    d = str(tmp_path_factory.mktemp("folders"))
    spark.read.parquet(f"{sf_dir}/documents.parquet").repartition(3).write.parquet(f"{d}/documents.parquet")
    plans.load()
    return d


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_f14_attrition_of_a_stream_from_a_folder(spark, sf_dir, folders):
    q = registry.QUERIES["q_stream_attrition"]
    assert rows(q(spark, folders)) == rows(q(spark, sf_dir)) != []


def test_f15_documents_of_a_stream_from_a_folder(spark, sf_dir, folders):
    q = registry.QUERIES["q_stream_documents"]
    assert rows(q(spark, folders)) == rows(q(spark, sf_dir)) != []


def test_f16_near_copies_of_a_stream_from_a_folder(spark, sf_dir, folders):
    q = registry.QUERIES["q_stream_near"]
    assert rows(q(spark, folders)) == rows(q(spark, sf_dir)) != []


def test_f16_near_copies_over_several_batches(spark, folders):
    """One file a batch: state of earlier batches holds, and the same documents but one of each bucket are found."""
    docs = spark.readStream.schema(spark.read.parquet(f"{folders}/documents.parquet").schema).option("maxFilesPerTrigger", 1).parquet(f"{folders}/documents.parque[t]")
    bands_of = lambda df: dedup.signatures(df.select("doc_id", "lang", "text"), config.DEDUP_NGRAM, *dedup.bands_at_recall()).select("doc_id", F.posexplode("bands").alias("band", "h"))
    got = intake.near_copies_available(bands_of(docs))
    bands = bands_of(spark.read.parquet(f"{folders}/documents.parquet"))
    size = bands.groupBy("band", "h").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    assert got.count() == size.agg(F.sum(F.col("n") - 1)).first()[0]
    assert got.filter("doc_id = first").count() == 0 and got.select("band", "first").distinct().count() <= size.count()


@pytest.mark.parametrize("order,modified", [(5, True), (3, True), (2, False)])
def test_buckets_equal_the_joined_model(spark, sf_dir, order, modified):
    train, valid, new = q_lm.parts(spark, sf_dir)
    odd = spark.createDataFrame([(-1, "xx", "no model of this language"), (-2, None, "no language"), (-3, "en", None), (-4, "en", "... !"), (-5, "en", "neverseen wordsonly")], "doc_id long, lang string, text string")
    columns = ["doc_id", "lang", "text"]
    seqs = lm.sequences(valid.select(*columns).unionByName(new.select(*columns)).unionByName(odd))
    train = lm.sequences(train)
    want = {r["doc_id"]: r for r in lm.perplexity(seqs, lm.kneser_ney(train, order, modified), "join").collect()}
    got = {r["doc_id"]: r for r in lm_buckets.Bucketed(train, 3, order, modified).perplexity(seqs).collect()}
    assert got.keys() == want.keys() and {-4, -5} <= got.keys() and not {-1, -2, -3} & got.keys()
    assert all(got[i]["tokens"] == r["tokens"] and got[i]["lang"] == r["lang"] and abs(got[i]["ppl"] / r["ppl"] - 1) < 1e-9 for i, r in want.items())


def test_a_model_of_more_words_than_are_broadcast_is_joined(spark, sf_dir):
    train, valid, _ = q_lm.parts(spark, sf_dir)
    train, valid = lm.sequences(train.filter("doc_id < 40")), lm.sequences(valid.filter("doc_id < 40"))
    few, all_ = lm_buckets.Bucketed(train, 2, 3, most=1), lm_buckets.Bucketed(train, 2, 3)
    assert few.joined and not all_.joined
    want = {r["doc_id"]: r["ppl"] for r in all_.perplexity(valid).collect()}
    got = {r["doc_id"]: r["ppl"] for r in few.perplexity(valid).collect()}
    assert got.keys() == want.keys() and all(abs(got[i] / p - 1) < 1e-9 for i, p in want.items())


@pytest.mark.parametrize("name", ["q_ppl_5gram", "q_ppl_5gram_joined", "q_ppl_subword", "q_ppl_threshold", "q_ppl_filter", "q_ppl_report", "q_ppl_hist", "q_ppl_spread", "q_ppl_sweep", "q_ppl_buckets", "q_unverified_flow"])
def test_perplexities_take_neither_the_driver_nor_joins(spark, sf_dir, monkeypatch, name):
    """No model is compiled on the driver, and none is written and joined as tables of n-grams."""
    plans.load()

    def refuse(*_, **__):
        raise AssertionError("a whole model")

    monkeypatch.setattr(lm, "compile_model", refuse)
    monkeypatch.setattr(lm, "_score_joined", refuse)
    assert registry.QUERIES[name](spark, sf_dir).columns


def in_duckdb(sf_dir, name):
    import duckdb

    con = duckdb.connect()
    for t in ("documents", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return sorted(con.execute(registry.ORACLES[name]).fetchall())


def same(a, b):
    return len(a) == len(b) and all(abs(x - y) < 1e-9 if isinstance(x, float) else x == y for r, s in zip(a, b, strict=True) for x, y in zip(r, s, strict=True))


def test_f2_commonest_grams_are_not_shuffled(spark, sf_dir):
    plans.load()
    df = registry.QUERIES["q_flag_charrep"](spark, sf_dir)
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" not in plan and "Aggregate" not in plan
    assert same(rows(df), in_duckdb(sf_dir, "q_flag_charrep"))
    odd = spark.createDataFrame([(1, "abcdefghi"), (2, "abcdefghij"), (3, "ab" * 10), (4, None), (5, "é😀" * 6)], "doc_id long, text string")
    from textquarry.operators import signals

    got = dict(rows(odd.filter(F.length("text") >= 10).select("doc_id", F.pandas_udf(signals.top_gram_share, "double")("text"))))
    assert got == {2: 1.0, 3: 6 / 11, 5: 2 / 3}


@pytest.mark.parametrize("name,table", [("q_crowd_axes", "conversations"), ("q_source_python", "documents"), ("q_thresholds", "documents")])
def test_f19_f24_f26_read_a_given_table(spark, sf_dir, name, table):
    plans.load()
    assert table in registry.ORACLES[name]
    got = rows(registry.QUERIES[name](spark, sf_dir))
    assert got and same(got, in_duckdb(sf_dir, name))


def shuffled(spark) -> dict[str, int]:
    """Shuffle files that are on disk now, with their sizes."""
    files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    held = [files.apply(i) for i in range(files.size())]
    return {f.getName(): f.length() for f in held if f.getName().startswith("shuffle_") and f.getName().endswith(".data")}


@pytest.mark.parametrize("name", ["q_ppl_report", "q_ppl_hist"])
def test_f6_to_f12_packets_leave_the_disk(spark, sf_dir, tmp_path, name):
    """Packets of positions are on disk until they are scored, not until the query ends."""
    plans.load()
    spark.read.parquet(f"{sf_dir}/documents.parquet").repartition(4).write.parquet(f"{tmp_path}/documents.parquet")
    sf_dir, before = str(tmp_path), shuffled(spark)
    registry.QUERIES[name](spark, sf_dir)
    for _ in range(50):
        left = sum(size for f, size in shuffled(spark).items() if f not in before)
        if left < 10_000:
            break
        time.sleep(0.2)
    assert left < 10_000


def test_f11_pieces_are_those_of_the_library(monkeypatch):
    """Words are cut once each, also beyond what is kept of them; blanks of any number and place as the library has them."""
    import public_tokenizers
    import pyarrow as pa

    pieces = lm.Pieces(public_tokenizers.path("piece_bpe_32k.model"))
    assert pieces.apart
    names = [pieces.model.id_to_piece(i) for i in range(len(pieces.hashes) - 2)] + ["<s>", "</s>"]
    odd = ["a  b", "▁", "a▁", "▁a▁▁b", " ▁ x", "日本 語 😀", "\tx \t y\xa0z", "a▁▁▁", "é ê  z", "x" * 3000, "<s> </s> <0x0A>", "a" + " " * 40 + "b", "the the the."]
    want = [["<s>", *x, "</s>"] for x in pieces.model.encode(odd, out_type=str)]

    def got(sentences):
        size, cut = pieces.cut(sentences)
        ends = size.cumsum()
        return [[names[i] for i in cut[end - n : end]] for n, end in zip(size, ends, strict=True)]

    assert got(pa.array(odd)) == want == got(pa.array(odd))
    assert got(pa.array(["before", *odd]).slice(1)) == want
    monkeypatch.setattr(pieces, "MOST", 3)
    assert [got(pa.array([x]))[0] for x in odd] == want
    monkeypatch.setattr(pieces, "apart", False)
    assert got(pa.array(odd)) == want


@pytest.mark.parametrize("order", [5, 2])
def test_f11_pieces_cut_where_they_are_packed(spark, sf_dir, monkeypatch, order):
    """The same perplexities as from lists of pieces by joins, and no list of pieces is made."""
    import public_tokenizers

    file = public_tokenizers.path("piece_bpe_32k.model")
    train, valid, _ = q_lm.parts(spark, sf_dir)
    odd = spark.createDataFrame([(-1, "xx", "no model of this language"), (-2, None, "no language"), (-3, "en", None), (-4, "en", "... !"), (-5, "en", "▁ 日本  語😀 x▁\n\ny")], "doc_id long, lang string, text string")
    some = train.filter("doc_id < 120"), valid.select("doc_id", "lang", "text").filter("doc_id < 120").unionByName(odd)
    model = lm.kneser_ney(lm.subword_sequences(some[0], file), order)
    want = {r["doc_id"]: r for r in lm.perplexity(lm.subword_sequences(some[1], file), model, "join").collect()}

    def refuse(*_, **__):
        raise AssertionError("lists of pieces")

    monkeypatch.setattr(lm, "subword_sequences", refuse)
    docs = [lm.Subwords(x, file) for x in some]
    got = {r["doc_id"]: r for r in lm_buckets.Bucketed(docs[0], 3, order).perplexity(docs[1]).collect()}
    assert got.keys() == want.keys() and {-4, -5} <= got.keys() and not {-1, -2, -3} & got.keys()
    assert all(got[i]["tokens"] == r["tokens"] and got[i]["lang"] == r["lang"] and abs(got[i]["ppl"] / r["ppl"] - 1) < 1e-9 for i, r in want.items())
    plans.load()
    assert registry.QUERIES["q_ppl_subword"](spark, sf_dir).count()


def test_f11_hashes_are_found_by_their_leading_bits():
    import numpy as np

    draw = np.random.default_rng(0)
    top = np.uint64((1 << 64) - 1)
    for n in (0, 1, 2, 3, 1000, 4097):
        keys = np.unique(draw.integers(0, 1 << 63, n, np.uint64) * np.uint64(2))
        for held in (keys, np.append(keys, top), np.arange(n, dtype=np.uint64)):
            wanted = np.concatenate([held, keys + np.uint64(1), draw.integers(0, 1 << 63, 50, np.uint64), np.array([0, top], np.uint64)])
            at, hit = lm_buckets._Keys(held).find(wanted)
            assert (hit == np.isin(wanted, held)).all() and (held[at[hit]] == wanted[hit]).all()
