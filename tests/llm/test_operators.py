"""Each operator against a plain version, on small and awkward tables."""

from __future__ import annotations

import hashlib
import itertools
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest

from textquarry.llm import bpe, jaccard, linededup, ordermin, packing, pii, quality, secrets, topk, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, extra string"
TOKEN = "password=Abcdef123456"


def frame(spark, texts, ids=None):
    rows = [(i if ids is None else ids[i], t, "en", f"src{i % 3}", len(t or ""), "x") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA)


AWKWARD = [None, "", " ", "\n\n", "a", "a", "ÀÉ ß \U0001f600", "word " * 3000, "x" * 5000, "\x01\x02 " + TOKEN]


def test_pii_plain_and_disguised(spark):
    cases = {
        "john dot doe at example dot com": ["email"],
        "jane [at] mail (dot) example (dot) org": ["email"],
        "４111 1111 1111 1111": ["card"],
        "plus 1 five five five one two three four five six seven": ["phone"],
        "look at the dot com boom": [],
    }
    for text, kinds in cases.items():
        plain = pii.plain_spans(text)
        assert not any(plain.values())
        added = pii.disguised_spans(text, plain)
        assert [k for k in pii.KINDS if added[k]] == kinds
        for spans in added.values():
            for a, b in spans:
                assert 0 <= a < b <= len(text)
    text = "a@b.co x 1.2.3.4 x 4111 1111 1111 1111 x +1 (988) 555-2485 x 999.1.1.1"
    assert {k: [text[a:b] for a, b in v] for k, v in pii.plain_spans(text).items()} == {"email": ["a@b.co"], "ip": ["1.2.3.4"], "card": ["4111 1111 1111 1111"], "phone": ["+1 (988) 555-2485"]}


def test_pii_plain_equals_regex():
    rng = random.Random(3)
    email = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
    ip = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
    for _ in range(3000):
        text = "".join(rng.choice("ab1@@..- +") for _ in range(rng.randint(0, 40)))
        assert pii.plain_spans(text)["email"] == [m.span() for m in email.finditer(text)]
        digits = "".join(rng.choice("123..") for _ in range(rng.randint(0, 40)))
        assert pii.plain_spans(digits)["ip"] == [m.span() for m in ip.finditer(digits) if all(int(p) <= 255 for p in m.group().split("."))]


def test_pii_awkward(spark):
    out = pii.pii_digest(frame(spark, AWKWARD)).collect()
    assert len(out) == len(AWKWARD)
    assert out[0]["base_sha256"] == hashlib.sha256(b"").hexdigest()
    assert pii.pii_digest(frame(spark, [])).count() == 0
    assert pii.redact(frame(spark, ["mail a@b.co now", None])).collect()[0]["text"] == "mail <EMAIL> now"


def test_pii_disguises_that_hold_a_plain_piece(spark):
    whole = {
        "write j\u043ehn@example.com now": "j\u043ehn@example.com",
        "write jane dot doe@example.com now": "jane dot doe@example.com",
        "write jane@mail.example dot com now": "jane@mail.example dot com",
        "write jane@example.c\u043em now": "jane@example.c\u043em",
    }
    for text, address in whole.items():
        plain = pii.plain_spans(text)
        added = pii.disguised_spans(text, plain)
        assert [text[a:b] for a, b in added["email"]] == [address]
    out = {r["text"] for r in pii.redact(frame(spark, list(whole))).collect()}
    assert out == {"write <EMAIL> now"}
    text = "ask\u2014a@b.co\u2014thanks"
    assert not any(pii.disguised_spans(text, pii.plain_spans(text)).values())
    text = "a@b.co and \uff41@b.co"  # plain spans are not added again
    assert pii.disguised_spans(text, pii.plain_spans(text))["email"] == [(11, 17)]


def test_pii_loose_disguises():
    cases = {
        "call +1 five five five 123 4567 now": ("phone", "+1 five five five 123 4567"),
        "call +1 555 one two three 4567 now": ("phone", "+1 555 one two three 4567"),
        "pay 4111 1111 1111 one one one 1 now": ("card", "4111 1111 1111 one one one 1"),
        "ping 192 dot 168 dot 1 dot 1 now": ("ip", "192 dot 168 dot 1 dot 1"),
        "ping 192 dot one six eight dot one dot one now": ("ip", "192 dot one six eight dot one dot one"),
        "ask jane dot doe at example.com now": ("email", "jane dot doe at example.com"),
        "ask jane at example.com now": ("email", "jane at example.com"),
        "ask jane @ example dot com now": ("email", "jane @ example dot com"),
        **{f"ask jane at example dot {x} now": ("email", f"jane at example dot {x}") for x in "nz za ie kr gr tr me".split()},
    }
    for text, (kind, value) in cases.items():
        added = pii.disguised_spans(text, pii.plain_spans(text))
        assert [text[a:b] for a, b in added[kind]] == [value], text
    clean = ["look at example.com", "find us at example.com", "look at one point so far", "call +1 555 123 4567 one day", "in 2010 two of 3 point 5 won", "meet at noon. Me too"]
    for text in clean:
        assert not any(pii.disguised_spans(text, pii.plain_spans(text)).values()), text


def brute_classes(texts, n=5, tau=0.8):
    def grams(t):
        w = [m.lower() for m in re.findall(r"[A-Za-z0-9_\u0080-\U0010ffff]+", t or "")]
        return {tuple(w[k : k + n]) for k in range(max(1, len(w) - n + 1))} if w else {("raw", t or "")}

    sets = [grams(t) for t in texts]
    root = list(range(len(texts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, j in itertools.combinations(range(len(texts)), 2):
        if len(sets[i] & sets[j]) >= tau * len(sets[i] | sets[j]):
            a, b = sorted((find(i), find(j)))
            root[b] = a
    return [find(i) for i in range(len(texts))]


def near_copies(rng, groups=6, size=25):
    words = [f"w{k}" for k in range(500)]
    texts = []
    for _ in range(groups):
        base = [rng.choice(words) for _ in range(120)]
        for _ in range(size):
            new = list(base)
            for _ in range(rng.randint(0, 5)):
                new[rng.randrange(len(new))] = rng.choice(words)
            texts.append(" ".join(new))
    rng.shuffle(texts)
    return texts


def test_jaccard_join_equals_brute_force(spark):
    texts = near_copies(random.Random(5)) + ["", None, "one two", "one two", "...", "!!!"]
    members, links = jaccard.jaccard_join(frame(spark, texts))
    got = {r["doc_id"]: r["class_id"] for r in members.collect()}
    assert [got[i] for i in range(len(texts))] == brute_classes(texts)
    assert all(r["jaccard"] >= 0.8 for r in links.collect())


def test_jaccard_counts_every_link(spark, monkeypatch):
    texts = near_copies(random.Random(8), groups=2, size=60) + ["one two"] * 3
    texts += [" ".join(f"x{j}" if i == j else f"y{j}" for j in range(120)) for i in range(5, 45)]  # each linked to each
    sets = [frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) for w in (t.split() for t in texts)]
    distinct = {s: min(i for i, t in enumerate(sets) if t == s) for s in sets}
    want = {(min(distinct[a], distinct[b]), max(distinct[a], distinct[b])) for a, b in itertools.combinations(distinct, 2) if len(a & b) >= 0.8 * len(a | b)}
    for bounds in ({}, {"BLOCK_MEMBERS": 16, "TILE": 7, "LIGHT": 5, "COLUMNS": 9, "EXPANDED": 50}):
        for name, value in bounds.items():
            monkeypatch.setattr(jaccard, name, value)
        members, links = jaccard.jaccard_join(frame(spark, texts))
        assert sorted((r["x"], r["y"]) for r in links.collect()) == sorted(want)
        got = {r["doc_id"]: r["n_links"] for r in members.collect()}
        assert got == {i: sum(distinct[s] in pair for pair in want) for i, s in enumerate(sets)}
    assert max(got.values()) == 39


def test_jaccard_empty_and_keep_one(spark):
    assert jaccard.jaccard_join(frame(spark, []))[0].count() == 0
    kept = jaccard.keep_one(frame(spark, ["a b c d e f g", "a b c d e f g", "other words stand here now"]))
    assert sorted(r["doc_id"] for r in kept.collect()) == [0, 2]


def test_bands_reach_recall():
    b, r = jaccard.bands_for(0.8, 0.999)
    assert 1 - (1 - 0.8**r) ** b >= 0.999 and b * r <= 128


def test_components_of_a_path(spark):
    from textquarry.llm._tables import Workspace

    edges = spark.createDataFrame([(i, i + 1) for i in range(200)], "src long, dst long")
    got = jaccard.components(Workspace(spark, "test"), edges).collect()
    assert len(got) == 201 and {r["root"] for r in got} == {0}


def test_quality_separates_held_out(spark, sf_dir):
    docs, labels = (spark.read.parquet(f"{sf_dir}/../sf0.01/{t}.parquet") for t in ("documents", "labels"))
    rows = quality.quality_scores(docs, labels).join(labels, "doc_id").filter("held_out").collect()
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in rows)
    assert np.mean([r["predicted"] == r["quality"] for r in rows]) >= 0.95
    assert all(0 <= r["score"] <= 1 for r in rows)


def test_quality_awkward(spark):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    out = quality.quality_scores(frame(spark, AWKWARD), labels).collect()
    assert len(out) == len(AWKWARD) and all(r["score"] == 0.5 for r in out)
    assert quality.pool_adjacent(np.array([0.5, 0.2, 0.9]), np.ones(3)).tolist() == [0.35, 0.35, 0.9]


@pytest.mark.parametrize("k", [3, 20])
def test_top_k_equals_brute_force(spark, k):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(300, 8)).astype(np.float32)
    x[50:150] = x[50]
    rows = [(i, v.tolist(), "x") for i, v in enumerate(x)] + [(900, None, "x"), (901, [float("nan")] * 8, "x"), (902, [None] * 8, "x")]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, extra string")
    ints = np.floor(64 * x.astype(np.float64)).astype(int)
    got = {}
    for r in topk.top_k(df, df.filter("vec_id % 20 = 0"), k).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    assert sorted(got) == list(range(0, 300, 20))
    for q in got:
        s = ints @ ints[q]
        want = sorted((-int(s[i]), i) for i in range(300) if i != q)[:k]
        assert sorted(got[q]) == [(n + 1, i, -v) for n, (v, i) in enumerate(want)]


def brute_secrets(text):
    text = text or ""
    found = []
    for m in re.finditer(r"""(?:[pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text):
        if len(m[1]) >= 6:
            found.append((m.start(), 0, "assign", m.end()))
    found += [(m.start(), 1, "access", m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    found += [(m.start(), 2, "hex", m.end()) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
    return hashlib.sha256(",".join(f"{k}:{a}:{b}" for a, _, k, b in sorted(found)).encode()).hexdigest()


def test_secret_scan_plain_equals_brute_force(spark):
    rng = random.Random(2)
    parts = ["é ", "token = \"abcdef99\"", "secret=token=abc", "AKIA" + "Z9" * 9, "0123456789abcdef" * 2, "Api_Key: 'zz", "passwd=1234567", " = ", "\n", "\x01", "\x04x"]
    texts = AWKWARD + ["".join(rng.choice(parts) for _ in range(rng.randint(0, 12))) for _ in range(200)]
    got = {r["doc_id"]: r["base_sha256"] for r in secrets.secret_digest(frame(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == [brute_secrets(t) for t in texts]


def test_secret_ownership(spark):
    live, example = "password=Zz9Kq77LmnP", "password=Example123"
    docs = frame(spark, [live, example, example, example, "AbCd1234EfGh5678IjKl9012 x", None])
    out = {r["doc_id"]: r["text"] for r in secrets.redact_live(docs).collect()}
    assert out[0] == "password=<SECRET>" and out[1] == example and "<SECRET>" in out[4] and out[5] is None


def test_secret_owner_counts(spark):
    one, two, copied, many = "Zz9Kq77LmnP01", "Yy8Jp66KloO02", "Xx7Io55JkmN03", "Ww6Hn44IjlM04"
    rows = [(f"own {i} password={one}", "a") for i in range(6)]  # one owner, six documents
    rows += [(f"shared {o} password={two}", o) for o in "ab"]  # two owners
    rows += [(f"copy password={copied}", o) for o in "abcdef"]  # one text, six owners
    rows += [(f"manual {o} password={many}", o) for o in "abcde"]  # a widely copied example
    rows += [("nothing", o) for o in "ghi"]
    docs = spark.createDataFrame([(i, t, o) for i, (t, o) in enumerate(rows)], "doc_id long, text string, source string")
    out = {r["doc_id"]: r["text"] for r in secrets.redact_live(docs).collect()}
    assert [out[i].endswith("<SECRET>") for i in range(len(rows))] == [True] * 14 + [False] * 8
    assert {r["n_live"] for r in secrets.secret_digest(docs).collect() if r["doc_id"] < 14} == {1}


def test_toxicity_held_out_and_swaps(spark, sf_dir):
    docs, labels = (spark.read.parquet(f"{sf_dir}/../sf0.01/{t}.parquet") for t in ("documents", "labels"))
    rows = toxicity.toxicity_scores(docs, labels).join(labels, "doc_id").filter("held_out").collect()
    assert len(rows) > 50 and np.mean([r["predicted"] == r["toxic"] for r in rows]) >= 0.93
    # Texts in which one term goes with the label: the penalty holds scores still, and neutral mentions are called toxic less often.
    rng = random.Random(1)
    texts, ys = [], []
    for i in range(800):
        toxic = i % 2
        group = "women" if rng.random() < (0.95 if toxic else 0.05) else "men"
        insult = rng.choice(("scum", "idiot", "trash", "clown")) if rng.random() < 0.6 else rng.choice(("garden", "river", "table", "letter"))
        texts.append(f"some {group} said {insult if toxic else rng.choice(('garden', 'river', 'table', 'letter', 'hello'))} w{i}")
        ys.append(toxic)
    train = spark.createDataFrame(list(zip(texts, ys, strict=True)), "text string, y int")
    neutral = spark.createDataFrame([(f"{g} like the {w}", 0) for g in ("women", "Women", "men") for w in ("garden", "river", "table")] + [("no term here", 0), (None, 0)], "text string, toxic int")
    free, tied = (toxicity.swap_report(neutral, toxicity.fit(train, swap_weight=w)).first() for w in (0.0, toxicity.SWAP))
    assert free["swaps"] == tied["swaps"] > 0
    assert tied["mean_change"] < 0.1 * free["mean_change"] and tied["flips"] == 0 < free["flips"]
    assert tied["called_toxic"] < free["called_toxic"]


def test_toxicity_swaps_are_made_in_the_text(spark):
    assert {t for t, _ in toxicity.swaps("Women, not womenfolk, and women")} == {f"{x}, not womenfolk, and {x}" for x in ("men", "girls", "boys")}
    assert sum(w for _, w in toxicity.swaps("women and men")) == 2
    assert list(toxicity.swaps("")) == []
    model = toxicity.Model(0.0)
    held = {t: np.unique(toxicity.word_features(np.frombuffer(t.encode(), np.uint8), np.array([0, len(t)]))[0]) for t in ("women", "men")}
    model.buckets = np.unique(np.concatenate(list(held.values())))
    one = spark.createDataFrame([("women",), ("women and men",)], "text string")
    rows = toxicity.swap_differences(one, model).collect()
    # A text that holds both terms loses one feature and gains none, or the other way round.
    assert any(r["gone"] and r["new"] for r in rows) and any(r["gone"] and not r["new"] for r in rows)


def test_line_dedup(spark):
    shared = "This line is long enough to be counted as shared text."
    texts = [f"own {i}\n  {shared.upper() if i % 2 else shared}\t\nend" for i in range(6)] + [None, "", shared + "é", shared]
    out = {r["doc_id"]: r for r in linededup.drop_shared_lines(frame(spark, texts)).collect()}
    assert [out[i]["n_dropped"] for i in range(10)] == [1, 1, 1, 1, 1, 1, 0, 0, 0, 0]
    assert out[0]["text"] == "own 0\nend" and out[9]["text"] == shared and out[6]["n_lines"] == 1
    assert linededup.line_digest(frame(spark, [])).count() == 0


def test_bpe_equals_tiktoken(spark):
    import public_tokenizers
    import tiktoken

    ranks = bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    texts = AWKWARD + ["It's we'll   don't 123 ½² naïve\tÜber\n\n  end ", "汉字 Привет   x", "thisisaninventedwordnobodyknows Thstinnt", "<|endoftext|>"]
    got = {r["doc_id"]: r for r in bpe.encode(frame(spark, texts), ranks, public_tokenizers.PATTERN).collect()}
    for i, t in enumerate(texts):
        assert list(got[i]["codes"]) == enc.encode_ordinary(t or "")
        assert bytes(got[i]["decoded"]) == (t or "").encode()
    rng = random.Random(4)
    for _ in range(200):
        w = "".join(rng.choice("abcdethino é") for _ in range(rng.randint(1, 400)))
        piece = w.encode()
        assert bpe.merge_by_heap(piece, ranks) == enc._encode_single_piece(w)


def test_order_minhash(spark):
    texts = AWKWARD + ["the quick brown fox jumps over the lazy dog again and again " * 3]
    rows = {r["doc_id"]: r for r in ordermin.fingerprint_edits(frame(spark, texts), range_bytes=3000).collect()}
    order = sorted(range(len(texts)), reverse=True)
    prints = {}
    for k, i in enumerate(order):
        t, u = texts[i] or "", texts[order[(k + 1) % len(order)]] or ""
        edited = t[: len(t) - len(t) // 2] + u[: len(t) // 2]
        assert rows[i]["n_chars"] == len(t)
        assert rows[i]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert prints.setdefault(t, rows[i]["fingerprint"]) == rows[i]["fingerprint"]
    base = "a b c d e f g h i j k l m n o p q r s t u v w x y z " * 4
    moved = base[52:] + base[:20]
    p = ordermin.fingerprints(pa.array([base, base, moved, "nothing alike at all in this one"]))
    near = lambda a, b: float((p[a] == p[b]).mean())
    assert near(0, 1) == 1 and near(0, 2) > near(0, 3)


def test_packing_is_exact_and_no_worse_than_first_fit(spark):
    rng = random.Random(7)
    texts = ["w " * rng.choice([0, 3, 200, 255, 256, 300, 900, 5000]) for _ in range(300)] + [None]
    rows = packing.pack(frame(spark, texts), group=100).collect()
    total, bins = {}, {}
    for r in rows:
        total[r["doc_id"]] = total.get(r["doc_id"], 0) + r["length"]
        if r["bin_id"] is not None:
            bins.setdefault(r["bin_id"], []).append(r)
    assert [total[i] for i in range(len(texts))] == [len((t or "").split()) for t in texts]
    for held in bins.values():
        held.sort(key=lambda r: r["offset"])
        assert all(a["offset"] + a["length"] == b["offset"] for a, b in itertools.pairwise(held))
        used = sum(r["length"] for r in held)
        assert held[0]["capacity"] == min(c for c in packing.CAPACITIES if c >= used)
    lengths = sorted((rng.randint(1, 4096) for _ in range(2000)), reverse=True)
    _, final = packing.pack_group(lengths)
    single = packing.best_fit(lengths, (4096,))[1]
    assert sum(map(packing.cost, final)) <= sum(map(packing.cost, single))


def test_pipeline_stages_take_effect(spark, sf_dir):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = docs.count()
        docs = corpus_pipeline.Workspace(spark, "test").write(stage(spark, docs, sf_dir))
        assert docs.columns == columns and 0 < docs.count() <= before, name
    assert docs.filter("n_chars <> length(text)").count() == 0
    assert corpus_pipeline.STAGES[-1][1](spark, docs, sf_dir).select("doc_id").distinct().count() == docs.count()
