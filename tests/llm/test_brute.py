"""Operators that SQL cannot state, over a given table, against plain Python; and their defined results on odd tables."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict
from math import log

import numpy as np
import pytest

P = pytest.importorskip("public_tokenizers")
from duelspark.llm import bpe, hnsw, langid, media, mixing, pii, queries, setsketch, sharding, urlfilter, viterbi  # noqa: E402

from . import brute  # noqa: E402

SMALL, SF = "/root/testdata/sf0.001", "/root/testdata/sf0.01"
SHAPE = "doc_id long, text string, lang string, source string, n_chars long, n_tokens string, id string, shard string, rank string"
LONG = ("one two three " * 70_000, "ein wort " * 70_000)


def odd(spark, texts):
    return spark.createDataFrame([(i, t, "en", "s", 0, "a", "b", "c", "d") for i, t in texts], SHAPE)


def table(spark, name, sf=SMALL):
    return spark.read.parquet(f"{sf}/{name}.parquet")


def test_pseudonyms_over_a_table(spark):
    """Shapes stay, whatever is replaced differs, and one value has one pseudonym in all documents."""
    texts = {r["doc_id"]: r["text"] for r in table(spark, "documents", SF).collect()}
    rows = queries.op1_feistel_pii(spark, SF).collect()
    shape = lambda t: re.sub(r"[^\W_]+", "x", t)  # noqa: E731  the parts of an address may grow or shrink
    number = re.compile(r"(?<![\w.-])\d{3}-\d{2}-\d{4}(?![\w-])|(?<![\w.])(?:\d{1,3}\.){3}\d{1,3}(?![\w.])")
    names, back, replaced = {}, {}, 0
    assert len(rows) == len(texts)
    for r in rows:
        old, new = texts[r["doc_id"]] or "", r["text"] or ""
        if not r["n_replaced"]:
            assert new == old
            continue
        replaced += 1
        assert new != old
        assert shape(new) == shape(old)
        was, now = number.findall(old), number.findall(new)
        assert len(was) == len(now)
        for x, y in zip(was, now, strict=True):
            if x != y:
                assert names.setdefault(x, y) == y and back.setdefault(y, x) == x
    assert replaced > 10 and len(names) > 5


def test_language_against_plain_naive_bayes(spark):
    """A plain classifier over the n-grams themselves, without hashing or numpy, says the same language."""
    rows = table(spark, "documents", SF).select("doc_id", "text", "lang").collect()
    held = lambda i: zlib.crc32(str(i).encode()) % 4 == 2

    def grams(text):
        t = "".join(c if c.isalpha() else " " for c in (text or "").lower()) + "  "
        return Counter(g for n in (1, 2, 3) for g in (t[i : i + n] for i in range(len(t) - 2)) if g.strip())

    counts, docs = defaultdict(Counter), Counter()
    for r in rows:
        if r["lang"] and r["text"] and not held(r["doc_id"]):
            counts[r["lang"]] += grams(r["text"])
            docs[r["lang"]] += 1
    total = {x: sum(c.values()) for x, c in counts.items()}
    got = {r["doc_id"]: r["lang_pred"] for r in queries.op2_naive_bayes_language(spark, SF).collect()}
    alike = asked = 0
    for r in rows[::3]:
        if (r["text"] or "").strip() and any(c.isalpha() for c in r["text"]):
            own = grams(r["text"][:20_000])
            score = {x: log(docs[x] / sum(docs.values())) + sum(n * log((counts[x][g] + 0.5) / (total[x] + 0.5 * 16384)) for g, n in own.items()) for x in counts}
            alike, asked = alike + (max(sorted(score), key=score.get) == got[r["doc_id"]]), asked + 1
    assert asked > 100 and alike / asked >= 0.99


def test_parts_of_long_texts_lose_nothing():
    text = "Aé1bc d. Zwei Wörter ohne " * 40
    whole = langid.pieces([text], 10**6)
    many = langid.pieces([text], 37)
    count = lambda parts: sum(np.bincount(langid.grams(group, 1 << 10, over)[0].ravel(), minlength=1025)[:1024] for _, group, over in parts)
    assert (count(whole) == count(many)).all()


def test_media_over_a_table(spark):
    texts = {r["doc_id"]: r["text"] for r in table(spark, "documents").collect()}
    for r in queries.op4_media_signatures(spark, SMALL).collect():
        raw = (texts[r["doc_id"]] or "").encode()
        payload = raw + b"\xff" * (-len(raw) % 576 or (0 if raw else 576))
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]))
        stored = media.store(payload, media.STORED[zlib.crc32(payload) % 3])
        assert (r["media_bytes"], r["media_sha256"]) == (len(stored), hashlib.sha256(stored).hexdigest())


def test_hostile_bytes_are_sniffed_in_time():
    finder = media.automaton()
    for blob in (b"%PDF-" * 100_000, b"\xff\xd8\xff\xda\x00\x02" * 50_000, b"\x89PNG\r\n\x1a\n" * 50_000, b"", None):
        assert media.sniff(blob, finder) == []


def test_rates_against_plain_projected_descent(spark):
    """Rates by plain projected gradient steps over the same posteriors reach the targets with the same expected tokens."""
    rows = queries.op5_soft_mixing(spark, SF).toPandas()
    names = list(mixing.Mixture().weights)
    share = np.array([mixing.Mixture().weights[n] for n in names])
    mass = rows[[f"p_{n}" for n in names]].to_numpy() * rows["tokens"].to_numpy()[:, None]
    targets = share / share.sum() * rows["tokens"].sum()
    plain = np.ones(len(rows))
    step = 1 / np.linalg.norm(mass.T @ mass, 2)
    for _ in range(20_000):
        plain = np.maximum(0, plain - step * (mass @ (plain @ mass - targets)))
    ours = rows["rate"].to_numpy()
    assert (ours >= 0).all() and np.abs(plain @ mass - targets).max() < 0.01 * targets.sum()
    assert np.abs(ours @ mass - targets).max() < 1e-3 * targets.sum()
    drawn = rows["copies"].to_numpy()
    assert (np.abs(drawn - ours) < 1 + 1e-6).all() and abs((drawn * rows["tokens"]).sum() / rows["tokens"].sum() - 1) < 0.1


def test_shards_over_a_table(spark):
    """Counts are at most one apart, slots have no gaps, and equal texts, apart from groups above a quota, are hardly cut."""
    texts = {r["doc_id"]: r["text"] for r in table(spark, "documents", SF).collect()}
    rows = queries.op8_balanced_shards(spark, SF).collect()
    sizes, slots, groups = Counter(r["shard"] for r in rows), defaultdict(list), defaultdict(list)
    for r in rows:
        raw = (texts[r["doc_id"]] or "").encode()
        assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len(raw) + 8, zlib.crc32(raw), "rows", None)
        slots[r["shard"]].append(r["slot"])
        groups[texts[r["doc_id"]]].append(r["shard"])
    assert len(rows) == len(texts) and set(sizes) == set(range(24)) and max(sizes.values()) - min(sizes.values()) <= 1
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    small = [g for g in groups.values() if 1 < len(g) <= len(rows) // 24]
    assert small and sum(len(set(g)) > 1 for g in small) <= 24 + 0.1 * len(small)


def test_viterbi_over_a_table(spark):
    """Counts over whole texts of a table equal those of the tokenizers library."""
    from tokenizers import Tokenizer, models, pre_tokenizers

    path = P.path("piece_bpe_32k.model")
    normal = [(p, s) for p, s, kind in viterbi.load_pieces(path) if kind == "normal"]
    low = min(s for _, s in normal)
    tokenizer = Tokenizer(models.Unigram([("<unk>", 0.0), *((f"<0x{b:02X}>", low) for b in range(256)), *normal], 0, True))
    tokenizer.pre_tokenizer = pre_tokenizers.Metaspace()
    texts = {r["doc_id"]: r["text"] for r in table(spark, "documents").collect()}
    got = queries.op7_viterbi_counts(spark, SMALL).collect()
    assert len(got) == len(texts)
    for r in got:
        assert r["n_tokens"] == len(tokenizer.encode(texts[r["doc_id"]] or "", add_special_tokens=False).ids)


def test_registers_find_what_all_pairs_find(spark):
    docs = table(spark, "documents", SF)
    want = brute.near_duplicates([(r["doc_id"], r["text"]) for r in docs.collect()])
    for r in queries.op10_setsketch_dedup(spark, SF).collect():
        assert (r["n_shingles"], r["component_id"]) == want[r["doc_id"]]


def runs(spark):
    labels = table(spark, "labels")
    path, pieces = P.path("byte_bpe_50k.tiktoken"), P.path("piece_bpe_32k.model")
    model = langid.train(table(spark, "documents"))
    return {
        "pii": pii.report,
        "masked": pii.pseudonymise,
        "language": lambda d: langid.identify(d, model),
        "accepted": lambda d: langid.accepted(d, model),
        "media": media.text_media,
        "rates": lambda d: mixing.rates(d, labels),
        "resampled": lambda d: mixing.resampled(d, labels),
        "bpe": lambda d: bpe.round_trip(d, path, P.PATTERN),
        "viterbi": lambda d: viterbi.count_tokens(d, pieces),
        "shards": sharding.shard_texts,
        "dedup": setsketch.near_duplicates,
        "kept": setsketch.without_copies,
    }


def test_empty_tables(spark):
    none = odd(spark, [])
    for name, run in runs(spark).items():
        assert run(none).count() == 0, name
    assert urlfilter.judge_urls(spark.createDataFrame([], "page_id long, url string, host string")).count() == 0
    assert hnsw.nearest(spark.createDataFrame([], "vec_id long, embedding array<float>, rank int")).count() == 0
    docs = table(spark, "documents")
    assert mixing.rates(docs, table(spark, "labels").where("false")).count() == docs.count()


def test_odd_rows(spark):
    """Nulls, empty and very long texts, repeated rows and columns of clashing names: every row is answered, equal rows alike."""
    texts = [(1, None), (2, ""), (3, " \n"), (4, LONG[0]), (5, LONG[1]), (6, "a b c d e f"), (6, "a b c d e f"), (None, "no id"), (8, "漢字 😀 \x00 ß")]
    docs = odd(spark, texts)
    for name, run in runs(spark).items():
        rows = run(docs).collect()
        if name in ("accepted", "resampled", "kept", "masked"):
            assert set(rows[0].__fields__) == set(docs.columns), name
        if name not in ("accepted", "resampled", "kept"):
            assert len(rows) == len(texts), name
            twins = [r.asDict() for r in rows if r["doc_id"] == 6]
            assert len(twins) == 2, name
            if name != "shards":
                assert twins[0] == twins[1], name


def test_vectors_that_repeat_or_are_doubles(spark):
    rows = [(0, [1.0, 0.0]), (0, [1.0, 0.0]), (1, [1.0 + 1e-12, 0.0]), (2, [1.0 + 2e-12, 0.0]), (2, [1.0 + 2e-12, 0.0]), (3, [0.0, 1.0])]
    got = hnsw.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).orderBy("rank").collect()
    assert [(r["query_id"], r["rank"], r["vec_id"]) for r in got] == [(0, 1, 1), (0, 2, 2), (0, 3, 3)]
    assert 0 < got[0]["score"] < got[1]["score"] < 1e-11


def test_a_full_shard_is_searched_well(spark):
    """Recall on 4,000 random unit vectors in one shard, with the default beam."""
    rng = np.random.default_rng(9)
    x = rng.normal(size=(4000, 32)).astype(np.float32)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    got = hnsw.nearest(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")).toPandas()
    hits = 0
    for q, part in got.groupby("query_id"):
        d = ((x.astype(float) - x[q].astype(float)) ** 2).sum(axis=1)
        d[q] = np.inf
        hits += len(set(np.argsort(d, kind="stable")[:10]) & set(part["vec_id"]))
    assert hits / 400 >= 0.95


def test_pipeline_against_plain_stages(spark):
    """What the stages keep, by plain versions of their decisions."""
    import corpus_pipeline

    docs = table(spark, "documents")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    kept = corpus_pipeline.identify_language(spark, docs, SMALL)
    ids = {r["doc_id"] for r in kept.select("doc_id").collect()}
    lettered = {i for i, t in texts.items() if any(c.isalpha() for c in t or "")}
    assert ids <= lettered and len(ids) >= 0.98 * len(lettered)
    want = brute.near_duplicates([(i, texts[i]) for i in ids])
    single = corpus_pipeline.drop_near_duplicates(spark, kept, SMALL)
    assert {r["doc_id"] for r in single.select("doc_id").collect()} == {i for i, (_, c) in want.items() if i == c}
    masked = corpus_pipeline.pseudonymise(spark, single, SMALL)
    names = pii.Pseudonyms()
    assert all(r["text"] == names.apply(texts[r["doc_id"]])[0] for r in masked.collect())
    mixed = corpus_pipeline.mix_sources(spark, masked, SMALL)
    counts = {r["doc_id"]: r["copies"] for r in mixing.rates(masked, table(spark, "labels")).collect()}
    taken = Counter(r["doc_id"] for r in mixed.select("doc_id").collect())
    assert taken == {i: n for i, n in counts.items() if n}
    decoded = {r["doc_id"]: r["decoded_sha256"] for r in corpus_pipeline.encode_bytes(spark, mixed, SMALL).collect()}
    assert decoded == {r["doc_id"]: hashlib.sha256((r["text"] or "").encode()).hexdigest() for r in mixed.collect()}
