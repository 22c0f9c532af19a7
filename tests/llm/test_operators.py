"""The training-data operators against plain versions, round trips and their defined results."""

import base64
import hashlib
import os
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
import tiktoken
from pyspark.sql import functions as F
from tokenizers import Tokenizer, models, pre_tokenizers

from . import brute

P = pytest.importorskip("public_tokenizers")
from duelspark.llm import bpe, hnsw, langid, media, mixing, pii, queries, setsketch, sharding, urlfilter, viterbi  # noqa: E402

SF = "/root/testdata/sf0.001"
ODD = [(1, None), (2, ""), (3, "   \n\t"), (4, "one two"), (5, "one two"), (6, "…漢字 ÀÉ ß"), (7, "word " * 30_000), (7, "word " * 30_000), (None, "no id here at all")]


def odd(spark):
    rows = [(i, t, "en", "s", 0, "clash") for i, t in ODD]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, n_tokens string")


def test_pseudonyms_keep_formats():
    names = pii.Pseudonyms()
    assert sorted(names.permute(i, 997, "x") for i in range(997)) == list(range(997))
    text = "mail that.92@mail2.example.com card 4785380592391139, ip 8.196.197.208 phone +1 (743) 555-3824 on 1999-12-31; 078-05-1120"
    new, counts = names.apply(text)
    assert counts == dict.fromkeys(("email", "card", "ip", "phone", "date", "ssn"), 1) and len(new.split()) == len(text.split())
    assert not {"4785380592391139", "8.196.197.208", "1999-12-31"} & set(new.replace(",", "").replace(";", "").split())
    card = next(w for w in new.replace(",", "").split() if len(w) == 16 and w.isdigit())
    assert pii._luhn(card) == 0 and names.apply(new)[1]["card"] == 1
    assert names.apply("again 4785380592391139")[0].split()[1] == card
    for clean in (None, "", "no data 12345 1.2.3 2123465659789240", "31.02.1999"):
        assert names.apply(clean) == (clean, {})
    assert names.apply("12 4785380592391139")[0] == f"12 {card}"
    assert names.apply("DE89 3704 0044 0532 0130 00")[1] == {"iban": 1} and names.apply("DE88 3704 0044 0532 0130 00")[1] == {}


def test_language(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = langid.identify(docs, langid.train(docs)).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert (got["lang_pred"] == got["lang"]).mean() > 0.98
    rows = {r["doc_id"]: r for r in langid.identify(odd(spark), langid.train(docs)).collect()}
    assert all(rows[i]["lang_pred"] == "und" and rows[i]["score"] == 0 for i in (1, 2, 3)) and rows[7]["lang_pred"] == "en"
    empty = langid.train(docs.where("false"))
    assert {r["lang_pred"] for r in langid.identify(docs, empty).collect()} == {"und"}
    assert langid.accepted(odd(spark), langid.train(docs)).columns == odd(spark).columns


def test_urls(spark):
    pages = [(1, "http://A.Example.COM/de/x?y"), (2, "https://x.org/fr/1"), (3, "http://b.net/spam"), (4, "http://example.net/en/xxx"), (5, "http://e.com/cheap-loan"), (6, "http://e.com/cheap-cheap"), (7, "xxx"), (8, None), (9, "http://essex.com/axxx"), (10, "http://n.net")]
    got = {r["page_id"]: r for r in urlfilter.judge_urls(spark.createDataFrame(pages, "page_id long, url string")).collect()}
    assert [got[i]["verdict"] for i in range(1, 11)] == ["block", "allow", "block", "allow", "block", "allow", "block", "allow", "allow", "allow"]
    assert (got[1]["host"], got[1]["path"], got[1]["rule"]) == ("a.example.com", "/de/x", "example.com/de/") and got[8]["host"] == ""


def test_media(spark):
    finder = media.automaton()
    rng = random.Random(1)
    for kind in media.STORED:
        payload = bytes(rng.randrange(256) for _ in range(media.UNIT * 3))
        blob = media.store(payload, kind)
        junk = b"BM RIFF \x89PNG %PDF- " * 5
        item, = media.sniff(junk + blob + junk, finder)
        assert (item.kind, item.samples, item.start, item.end) == (kind, payload, len(junk), len(junk) + len(blob))
        assert media.sniff(blob[:-1], finder) == []
    got = {r["doc_id"]: r for r in media.text_media(odd(spark)).collect()}
    assert got[1]["n_bytes"] == 0 and got[1]["payload_bytes"] == 576 and got[1]["payload_sha256"] == hashlib.sha256(b"\xff" * 576).hexdigest() and got[1]["tail_crc32"] == zlib.crc32(b"\xff" * 32)
    assert got[4]["feature"] == got[5]["feature"]
    blobs = spark.createDataFrame([(1, bytearray(junk + blob), "image/png"), (2, None, None)], "id long, blob binary, kind string")
    row, = media.sniff_column(blobs, "id", "blob", "kind").collect()
    assert row["kind"] == "image/bmp" and row["corrected"] and bytes(row["media"]) == blob


def test_mixing_meets_targets(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    got = mixing.rates(docs, labels).toPandas()
    weight = got["tokens"] * got["rate"]
    for name, share in mixing.Mixture().weights.items():
        assert abs((weight * got[f"p_{name}"]).sum() / weight.sum() - share) < 1e-3
    assert (got["rate"] >= 0).all() and len(got) == docs.count()
    assert mixing.resampled(odd(spark), labels).columns == odd(spark).columns


def test_byte_bpe(spark):
    path = P.path("byte_bpe_50k.tiktoken")
    with open(path, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    encoding = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    rng = random.Random(3)
    texts = [None, "", "漢字" * 50, "😀" * 5, "a" * 300, "".join(rng.choice("abcdefgh") for _ in range(2000)), "don't I'M  x \n\n y "]
    texts += ["".join(chr(rng.choice([rng.randrange(32, 0x250), rng.randrange(0x250, 0xD7FF), 32, 97])) for _ in range(30)) for _ in range(30)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for limits in ({}, {"remembered": 5}):
        for r in bpe.round_trip(df, path, P.PATTERN, **limits).collect():
            ids = encoding.encode_ordinary(texts[r["doc_id"]] or "")
            assert (r["n_tokens"], r["ids_sha256"]) == (len(ids), bpe.digest(ids))
            assert r["decoded_sha256"] == hashlib.sha256((texts[r["doc_id"]] or "").encode()).hexdigest()


def test_fold_steps_cost_little_and_keep_the_order_of_merges(spark):
    """One function runs over the words, none over the elements of a word; equal ranks that overlap are merged from the left."""
    path = P.path("byte_bpe_50k.tiktoken")
    vocabulary = bpe.Vocabulary.read(path)
    small = bpe.Merger(np.zeros(256, np.int64), np.zeros(3, np.int64), np.zeros(3, np.int32))
    expression = str(small.fold(F.col("w"), F.col("fresh")))
    assert expression.count("transform(") == 1 and "flatten(" not in expression
    rng, merger = random.Random(5), bpe.Merger.of(vocabulary)
    words = [b"a" * n for n in range(1, 40)] + [b" " * 200, b"ab" * 100, b"x" * 300] + [bytes(rng.choices(b"aeinorst lh", k=rng.randrange(1, 30))) for _ in range(300)]
    opened = merger.opened(words, 256, vocabulary.merge)
    table = pa.table({"w": pa.ListArray.from_arrays(pa.array([0, len(words)], pa.int32()), opened), "fresh": [""]})
    got = spark.createDataFrame(table).select(merger.fold(F.col("w"), F.col("fresh")).alias("w")).toArrow()
    ids, lengths = bpe.Merger.ids(got.column(0).chunk(0).flatten())
    assert [x.tolist() for x in np.split(ids, np.cumsum(lengths)[:-1])] == [vocabulary.merge(w) for w in words]


def test_viterbi_counts(spark):
    path = P.path("piece_bpe_32k.model")
    normal = [(p, s) for p, s, kind in viterbi.load_pieces(path) if kind == "normal"]
    low = min(s for _, s in normal)
    whole = [("<unk>", 0.0), *((f"<0x{b:02X}>", low) for b in range(256)), *normal]
    tokenizer = Tokenizer(models.Unigram(whole, 0, True))
    tokenizer.pre_tokenizer = pre_tokenizers.Metaspace()
    texts = ["", " ", "  a  b ", "漢字 😀😀 x", "a\nb", "ĀĀ\x00 ßẞ", "▁a", "in the thouou onerest."]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in viterbi.count_tokens(df, path).collect():
        assert r["n_tokens"] == len(tokenizer.encode(texts[r["doc_id"]], add_special_tokens=False).ids)


def test_shards(spark):
    rows = [(i, "hot" if i % 3 == 0 else f"text {i // 2}" if i % 5 == 0 else f"own {i}") for i in range(500)] + [(500, None), (501, None)]
    got = sharding.shard_texts(spark.createDataFrame(rows, "doc_id long, text string")).toPandas()
    sizes = got.groupby("shard").size()
    assert len(sizes) == 24 and sizes.max() - sizes.min() <= 1 and len(got) == len(rows)
    assert all(sorted(g["slot"]) == list(range(len(g))) for _, g in got.groupby("shard"))
    assert sharding.shard_texts(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_shard_propagation_moves_rows(spark):
    links = [(i, i - i % 4) for i in range(400) if i % 4] + [(i, 1000) for i in range(1001, 1200)]  # groups of four, and one above a quota
    nodes, links = spark.createDataFrame([(i,) for i in [*range(400), *range(1000, 1200)]], "id long"), spark.createDataFrame(links, "a long, b long")
    before, after = (sharding.propagate(nodes, links, 6, rounds) for rounds in (0, 4))
    moved = before.select("id", "shard").exceptAll(after.select("id", "shard")).count()
    assert moved > 200 and after.count() == 600
    small = links.where("a < 1000")
    assert sharding.cut_links(after, links) < 0.7 * sharding.cut_links(before, links) and sharding.cut_links(after, small) < 0.1 * sharding.cut_links(before, small)
    assert after.where("id < 400").groupBy("shard").count().agg({"count": "max"}).first()[0] <= 1.1 * 100


def test_shards_keep_small_groups_beside_a_hot_one(spark):
    labels = [(i, i % 6, None, None) for i in range(600, 1000)] + [(i, 0, i - i % 2, None) for i in range(60)] + [(i, 0 if i < 500 else i % 6, 100, 500) for i in range(100, 600)]
    got = sharding.level(spark.createDataFrame(labels, "id long, shard int, lead long, size long"), 6).toPandas()
    sizes = got.groupby("shard").size()
    assert len(got) == len(labels) and sizes.max() - sizes.min() <= 1 and all(sorted(g["slot"]) == list(range(len(g))) for _, g in got.groupby("shard"))
    assert set(got[got["id"] < 60]["shard"]) == {0}
    crowded = [(i, 0, i - i % 3, None) for i in range(600)]  # small groups alone above the quota move in runs
    got = sharding.level(spark.createDataFrame(crowded, "id long, shard int, lead long, size long"), 6).toPandas()
    got["lead"] = got["id"] - got["id"] % 3
    assert (got.groupby("lead")["shard"].nunique() > 1).sum() <= 6
    rows = [(i, "hot" if i % 3 == 0 else f"pair {i // 3}") for i in range(2400)]
    got = sharding.shard_texts(spark.createDataFrame(rows, "doc_id long, text string")).toPandas()
    got["text"] = got["doc_id"].map(dict(rows))
    assert (got[got["text"] != "hot"].groupby("text")["shard"].nunique() > 1).sum() <= 8


def test_nearest_neighbours(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(900, 16)).astype(np.float32)
    x[::3] = x[0]  # a third of all rows is one vector
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(5000, None), (5100, [0.0] * 16), (5200, [float("nan")] * 16), (5300, [1.0] * 3)]
    got = hnsw.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), graph=hnsw.Graph(shard_rows=200)).toPandas()
    hits = total = 0
    for q, part in got.groupby("query_id"):
        d = np.sqrt(((x.astype(float) - x[q].astype(float)) ** 2).sum(axis=1))
        d[q] = np.inf
        want = np.lexsort((np.arange(len(d)), d))[:10]
        hits, total = hits + len(set(want) & set(part["vec_id"])), total + 10
        assert list(part.sort_values("rank")["rank"]) == list(range(1, 11)) and 5300 not in set(part["vec_id"])
        np.testing.assert_allclose(part["score"], d[part["vec_id"]], rtol=1e-12)
    assert total == 90 and hits / total >= 0.9


def test_near_duplicates(spark):
    rng = random.Random(4)
    base = [f"w{rng.randrange(50)}" for _ in range(80)]
    rows = [(i, t) for i, t in ODD if i is not None and i < 7]
    for i in range(10, 90):
        words = list(base)
        for _ in range(rng.randrange(6)):
            words[rng.randrange(len(words))] = f"x{rng.randrange(1000)}"
        rows.append((i, " ".join(words)))
    rows += [(100 + i, " ".join(f"y{rng.randrange(10**6)}" for _ in range(30))) for i in range(30)]
    want = brute.near_duplicates(rows)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    for r in setsketch.near_duplicates(docs).collect():
        assert (r["n_shingles"], r["component_id"]) == want[r["doc_id"]] and r["kept"] == (r["doc_id"] == r["component_id"])
    kept = {r["doc_id"] for r in setsketch.without_copies(docs).collect()}
    assert kept == {i for i, (_, c) in want.items() if i == c}
    assert setsketch.near_duplicates(docs.where("false")).count() == 0


def test_sketches_merge_and_estimate():
    s = setsketch.Sketch()
    a, b = np.arange(1000, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15), np.arange(200, 1200, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    assert (setsketch.merge(s.registers(a), s.registers(b)) == s.registers(np.union1d(a, b))).all()
    j = s.likeliest(s.registers(a)[None], s.registers(b)[None], np.array([1000.0]), np.array([1000.0]))[0]
    assert abs(j - 800 / 1200) < 0.15


def test_given_tables_against_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    want = brute.near_duplicates([(r["doc_id"], r["text"]) for r in docs.collect()])
    for r in queries.op10_setsketch_dedup(spark, SF).collect():
        assert (r["n_shingles"], r["component_id"]) == want[r["doc_id"]]


def test_pipeline(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:3]:
        docs_after = stage(spark, docs, SF)
        assert docs_after.columns == docs.columns, name
        docs = docs_after
    assert 0 < docs.count() <= 200 and corpus_pipeline.run(spark, SF).where(F.col("n_tokens") > 0).count() > 0


def test_no_other_module_imports_this_subpackage():
    root = os.path.join(os.path.dirname(__file__), "..", "..", "duelspark")
    for folder, _, names in os.walk(root):
        for name in names:
            if name.endswith(".py") and "/llm" not in folder:
                with open(os.path.join(folder, name)) as file:
                    assert "llm" not in file.read(), name
