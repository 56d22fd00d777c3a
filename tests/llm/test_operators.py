"""The operators on small frames with nulls, empty and long texts, repeated rows, clashing columns and empty tables."""

import math

import brute
import pytest
from pyspark.sql import functions as F

from panelspark.llm import components, jaccard, language, media, mixing, neighbours, pieces, pii, queries, repeats, token_counts, toxicity

PASSAGE = "a long passage that many of the documents share with each other, word for word and byte for byte"
BASE = " ".join(f"word{k}" for k in range(60))
ROWS = [
    (1, BASE, "en", "src0"), (2, BASE, "en", "src0"), (3, BASE + " more", "fr", "src1"), (4, None, None, None), (5, "", "en", "src2"), (6, "two words", "en", "src0"),
    (7, "Two  WORDS", "de", "src0"), (8, "x " + PASSAGE + " y", "en", "src1"), (9, PASSAGE + " unlike", "en", "src3"), (10, "start " + PASSAGE, "es", "src9"), (2, BASE, "en", "src0"), (11, "é" * 200, "fr", "src0"),
    (12, "é" * 199, "fr", "src0"), (13, " \n\t ", "en", "src4"), (14, "long " * 3000, "en", "src5"),
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(*r, len(r[1] or ""), 0, "blob") for r in ROWS]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, bucket int, blob string")


def pairs():
    return [(r[0], r[1]) for r in ROWS]


def test_repeats(spark, docs):
    got = sorted(tuple(r) for r in repeats.without_repeats(docs, 50).collect())
    assert got == brute.without_repeats(pairs(), 50)
    assert repeats.without_repeats(docs.limit(0), 50).count() == 0


def test_jaccard(spark, docs):
    for width, top in ((3, 90), (5, 80)):
        want = brute.components(pairs(), width, top)
        got = {r["doc_id"]: r for r in jaccard.similar(docs, width, top, 100).collect()}
        assert {i: r["component_id"] for i, r in got.items()} == want
        assert all(got[i]["n_shingles"] == len(brute.shingles(t, width)) for i, t in pairs())
    assert jaccard.similar(docs.limit(0)).count() == 0
    kept = {r["doc_id"] for r in jaccard.representatives(docs, 3, 90, 100).collect()}
    assert kept == {i for i, c in brute.components(pairs(), 3, 90).items() if i == c}


def test_jaccard_in_sub_blocks(spark):
    import random

    rng = random.Random(4)
    words = [f"w{k}" for k in range(400)]
    rows = []
    for group in range(6):
        base = [rng.choice(words) for _ in range(60)]
        for _ in range(14):
            copy = list(base)
            for _ in range(rng.randrange(4)):
                copy[rng.randrange(60)] = rng.choice(words)
            rows.append((len(rows), " ".join(copy)))
    rng.shuffle(rows)
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    for width, top in ((3, 90), (5, 80)):
        want = brute.components(rows, width, top)
        for block_rows in (3, 512):
            got = {r["doc_id"]: r["component_id"] for r in jaccard.similar(frame, width, top, 100, block_rows=block_rows, bucket_bytes=2000).collect()}
            assert got == want
        assert len(set(want.values())) < len(rows)


def test_jaccard_links_through_a_null_id(spark):
    a = " ".join(f"w{k}" for k in range(100))
    rows = [(1, a + " x"), (None, a), (3, "y " + a), (None, None), (None, "alone and of no name"), (9, None)]
    got = {(r["doc_id"], r["n_shingles"]): r["component_id"] for r in jaccard.similar(spark.createDataFrame(rows, "doc_id long, text string"), 3, 98, 100).collect()}
    assert got == {(1, 99): 1, (None, 98): 1, (3, 99): 1, (None, 0): None, (None, 3): None, (9, 0): 9}


def test_components(spark):
    links = [(1, 2), (2, 3), (10, 11), (7, 7), (3, 9)] + [(100, 100 + k) for k in range(1, 60)] + [(200 + k, 201 + k) for k in range(30)]
    got = {r["node"]: r["root"] for r in components.components(spark.createDataFrame(links, "u long, v long")).collect()}
    assert got[9] == 1 and got[11] == 10 and got[159] == 100 and got[230] == 200 and 7 not in got


def test_personal_data(spark):
    texts = [
        None, "", "mail me: a.b+c@x-y.example.org, or d@e.f_g@h.i", "a@b", "host 10.0.0.255 and 1.2.3.256 and 1.2.3.4.5.6.7.8", "card 4111 1111 1111 1111 and 4111-1111-1111-1112",
        "call +49 (30) 1234-5678.", "+1", "IBAN DE89370400440532013000 or DE89370400440532013001", "é" * 50 + " x@y.zz", "1" * 5000, "a" * 20000 + "@", "+1 " + "2 " * 4000, "0001.2.3.0255",
    ]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in pii.digest(rows).collect():
        spans = [s for s in r["spans"].split(",") if s and not s.startswith("iban")]
        assert spans == brute.base_spans(texts[r["doc_id"]]), r["doc_id"]
    got = {r["doc_id"]: r for r in pii.digest(rows).collect()}
    assert got[8]["n_iban"] == 1 and got[8]["scores"].endswith("1.0")
    clean = {r["doc_id"]: r["text"] for r in pii.redacted(rows).collect()}
    assert clean[0] is None and clean[1] == "" and clean[2].startswith("mail me: <email>, or <email>") and clean[8] == "IBAN <iban> or DE89370400440532013001"
    assert not any(brute.base_spans(t) for t in clean.values() if t and "_" not in t)
    assert pii.digest(rows.limit(0)).count() == 0


def test_personal_data_in_many_places_and_beside_clashing_columns(spark):
    names = ["doc_id", "text", "n_chars", "row", "spans", "wanted", "reach", "cuts", "done", "hits_ip", "at_ip", "_t"]
    many = " and ".join(f"a{k}@b.org +4930{k:06d} 10.0.{k % 256}.1 ip" for k in range(700))
    texts = [many, "x" * 300 + many, None, "", "to 1.2.3.4@h.org +1 2.3.4.5678 9", "Token = \"24be64439e3e49cf46b2\" API_key:'abcdefghijklmnop' secret=abcdefghijklmnop1 password: short1"]
    rows = spark.createDataFrame([(k, t, len(t or ""), *["keep"] * 9) for k, t in enumerate(texts)], "doc_id long, text string, n_chars long, " + ", ".join(f"`{n}` string" for n in names[3:]))
    for r in pii.digest(rows).collect():
        assert [s for s in r["spans"].split(",") if s] == brute.base_spans(texts[r["doc_id"]]) + brute.secrets(texts[r["doc_id"]])
        assert r["n_spans"] == len([s for s in r["spans"].split(",") if s])
    out = {r["doc_id"]: r for r in pii.redacted(rows).collect()}
    for k, t in enumerate(texts):
        assert out[k]["text"] == brute.redacted(t) and out[k]["n_chars"] == len(out[k]["text"] or "") and all(out[k][n] == "keep" for n in names[3:])
    assert pii.with_spans(rows).columns == [*names, "_pii"] and pii.redacted(rows.limit(0)).columns == names


def test_token_counts_and_pieces(spark, docs):
    import sentencepiece

    path = queries.tokenizer("piece_bpe_32k.model")
    want = [len(x) for x in sentencepiece.SentencePieceProcessor(model_file=path).encode([t or "" for _, t in pairs()])]
    got = token_counts.token_counts(docs, path, chunk=1000, overlap=16).collect()
    assert [r["n_tokens"] for r in got] == want and [r["over_limit"] for r in got] == [w > 4096 for w in want]
    coded = pieces.encode(docs, path)
    assert all(r["round_trip"] for r in coded.collect())
    assert [r["text"] for r in pieces.decode(coded, path).collect()] == [t or "" for _, t in pairs()]


def test_mixing_keeps_every_row_and_the_shares(spark, docs):
    out = mixing.mixed(docs, {"src0": 2, "src1": 1}, rest=1, block_bytes=64)
    assert out.count() == len(ROWS) and out.columns[: len(docs.columns)] == docs.columns
    assert sorted(map(str, mixing.interleaved(docs, {"src0": 2}, 1, 64).collect())) == sorted(map(str, docs.collect()))
    many = spark.range(4000).select(F.col("id").alias("doc_id"), F.lit("x" * 100).alias("text"), F.when(F.col("id") % 3 == 0, "a").otherwise("b").alias("source"))
    rows = mixing.mixed(many, {"a": 1, "b": 2}, rest=0, block_bytes=1000).orderBy("_slot", "_place").collect()
    done, seen = {"a": 0, "b": 0}, 0
    for r in rows:
        done[r["source"]] += 100
        seen += 100
        if r["_balanced"]:
            assert abs(done["a"] - seen / 3) <= 2000 and r["_release"] <= r["_slot"] < r["_deadline"]
    assert mixing.mixed(docs.limit(0), {"src0": 1}).count() == 0


def test_neighbours_leave_out_unusable_vectors(spark):
    rows = [(i, [float(i % 7), float(i % 5), 1.0]) for i in range(60)] + [(100, None), (101, [0.0, 0.0, 0.0]), (102, [math.nan, 1.0, 1.0]), (103, [1.0, None, 1.0]), (104, [math.inf, 0.0, 0.0]), (0, [0.0, 0.0, 1.0])]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = neighbours.nearest(v, v.where("vec_id % 20 = 0"), k=5, shard_rows=16, block_rows=2).collect()
    sound = {i: x for i, x in rows if i < 100}
    for q in (0, 20, 40):
        mine = sorted((r["rank"], r["vec_id"], r["score"]) for r in got if r["query_id"] == q)
        want = sorted((math.dist(sound[q], x), i) for i, x in sound.items() if i != q)[:5]
        assert [(i, pytest.approx(d)) for _, i, d in mine] == [(i, d) for d, i in want]
    assert {r["query_id"] for r in got} == {0, 20, 40}
    assert neighbours.nearest(v.limit(0), v).count() == 0


def test_media_columns(spark, docs):
    got = media.text_media(docs).collect()
    assert [r["n_bytes"] for r in got] == [len((t or "").encode()) for _, t in pairs()]
    assert all(r["payload_bytes"] % 576 == 0 and r["payload_bytes"] > 0 for r in got)
    rows = spark.createDataFrame([(1, "image/png", bytearray(media.stored(b"\x80" * 10))), (2, "audio/wav", bytearray(media.stored(b"\x80" * 11))), (3, None, None)], "id long, kind string, body binary")
    out = {r["id"]: r for r in media.corrected(rows, "id", "kind", "body").collect()}
    assert out[1]["media_type"] == "wav" and not out[1]["declared_ok"] and out[2]["declared_ok"] and out[3]["media_type"] == "unknown"


def test_media_are_carved_with_their_bytes(spark):
    gif = b"GIF89a\x01\x00\x01\x00\x00\x00\x00,\x00\x00\x00\x00\x01\x00\x01\x00\x00\x02\x02D\x01\x00;"
    wave = media.stored(b"\x80" * 10)
    values = [b"ab" + gif + b"cd" + wave + gif, gif, None, b"", wave + gif, gif]
    rows = spark.createDataFrame([(k, None if v is None else bytearray(v), "extra") for k, v in enumerate(values)], "id long, body binary, content string")
    got = sorted((r["id"], r["number"], r["media_type"], bytes(r["content"])) for r in media.carved(rows, "id", "body").collect())
    assert got == [(0, 0, "gif", gif), (0, 1, "wav", wave), (0, 2, "gif", gif), (4, 0, "gif", gif)]
    assert media.carved(rows.limit(0), "id", "body").count() == 0 and media.corrected(rows.limit(0), "id", "content", "body").count() == 0


def test_media_digests_equal_plain_ones(spark, docs):
    want = sorted(brute.media_digest(i, t) for i, t in pairs())
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256"]
    got = sorted(tuple(r[n] for n in names) + (r["feature"].rpartition("/in=")[0],) for r in media.text_media(docs).collect())
    assert got == want
    assert media.text_media(docs.limit(0)).count() == 0


def test_language_and_toxicity_of_odd_tables(spark):
    rows = [(k, f"the house and the garden of number {k}", "en", "src") for k in range(30)] + [(100 + k, f"der garten und das haus mit nummer {k}", "de", None) for k in range(30)]
    rows += [(7, "the house", "en", "x")] * 40 + [(None, "the same", "en", "x"), (500, None, "en", "x"), (501, "", None, "x"), (502, "12 34", "de", "x")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string, h string").withColumn("bound", F.lit(1)).withColumn("r", F.lit(2))
    sample = language.training_sample(frame, 20).collect()
    assert len(sample) == len({(r["doc_id"], r["lang"]) for r in sample}) <= 40 and all(r["doc_id"] is not None and r["text"] is not None for r in sample)
    out = language.predict(frame, language.train(frame, 20)).collect()
    assert len(out) == len(rows) and {r["lang_pred"] for r in out if r["doc_id"] in (500, 501, 502)} == {"und"}
    assert all(r["lang_pred"] == ("en" if r["doc_id"] < 100 else "de") for r in out if r["doc_id"] is not None and r["doc_id"] < 200)
    assert {r["lang_pred"] for r in language.predict(frame, language.train(frame.limit(0), 20)).collect()} == {"und"}
    labels = spark.createDataFrame([(k, int(k >= 100), 1) for k in [*range(30), *range(100, 130)]] + [(7, 0, 1)] * 50 + [(None, 1, 1), (9, None, 1)], "doc_id long, toxic int, quality int")
    model = toxicity.train(frame, labels)
    score = {(r["doc_id"], r["text"]): r for r in toxicity.score(frame, model).join(frame, "doc_id", "left").collect()}
    assert len(toxicity.score(frame, model).collect()) == len(rows) and all(0 <= r["score"] <= 1 for r in score.values())
    assert toxicity.kept(frame, model).columns == frame.columns and toxicity.kept(frame.limit(0), model).count() == 0
    assert toxicity.kept(frame, toxicity.train(frame, labels.limit(0))).count() == len(rows)


def test_mixing_beside_clashing_columns(spark):
    rows = [(k, f"text {k}" * (k % 5), ["a", "b", None][k % 3], "keep", 1.5) for k in range(200)] + [(3, "again", "a", "keep", 1.5)] * 3 + [(None, None, "b", "keep", 1.5)]
    plain = spark.createDataFrame([r[:3] for r in rows], "doc_id long, text string, source string")
    clash = spark.createDataFrame(rows, "doc_id long, text string, source string, stream string, place double").withColumn("_h", F.lit(0)).withColumn("bytes", F.lit(0)).withColumn("row", F.lit("r"))
    order = lambda f: [(r["doc_id"], r["slot"], r["text"]) for r in f.orderBy("slot", "doc_id", "text").collect()]
    out = mixing.scheduled(clash, {"a": 2, "b": 1}, 1, 64)
    assert order(out) == order(mixing.scheduled(plain, {"a": 2, "b": 1}, 1, 64)) and {r["stream"] for r in out.collect()} == {"keep"} and len(out.collect()) == len(rows)


def test_pipeline_of_an_empty_table(spark, data):
    import corpus_pipeline

    empty = spark.read.parquet(f"{data}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        empty = stage(spark, empty, data)
        assert empty.count() == 0


def test_pipeline(spark, data):
    import corpus_pipeline

    docs = spark.read.parquet(f"{data}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    clean = stages["toxicity"](spark, docs, data)
    assert clean.columns == docs.columns and 0.8 * docs.count() < clean.count() < docs.count()
    single = stages["near copies"](spark, docs, data)
    want = brute.components([(r["doc_id"], r["text"]) for r in docs.collect()], 5, 80)
    assert {r["doc_id"] for r in single.collect()} == {i for i, c in want.items() if i == c}
    masked = stages["personal data"](spark, docs, data)
    assert masked.columns == docs.columns
    assert sorted((r["doc_id"], r["text"]) for r in masked.collect()) == sorted((r["doc_id"], brute.redacted(r["text"])) for r in docs.collect())
    assert stages["source mixing"](spark, docs, data).count() == docs.count()
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=queries.tokenizer("piece_bpe_32k.model"))
    coded = stages["subword pieces"](spark, docs, data).collect()
    assert all(r["round_trip"] for r in coded)
    assert sorted((r["doc_id"], r["ids"]) for r in coded) == sorted((r["doc_id"], library.encode(r["text"] or "")) for r in docs.collect())
    scores = {r["doc_id"]: r["score"] for r in toxicity.score(docs, toxicity.train(docs, spark.read.parquet(f"{data}/labels.parquet"))).collect()}
    assert {r["doc_id"] for r in clean.collect()} == {i for i, p in scores.items() if p < 0.3}


def test_pipeline_keeps_the_schedule(spark, data, docs):
    import corpus_pipeline
    from panelspark.llm.common import settled

    stages = dict(corpus_pipeline.STAGES)
    for rows in (docs, spark.read.parquet(f"{data}/documents.parquet")):
        mixed = settled(stages["source mixing"](spark, rows, data))  # written and read again, as run() does
        out = settled(stages["subword pieces"](spark, mixed.repartition(7), data)).orderBy("slot", "place", "doc_id")
        want = mixing.mixed(rows, queries.WEIGHTS, queries.REST_WEIGHT, queries.BLOCK_BYTES).orderBy("_slot", "_place", "doc_id")
        assert [tuple(r) for r in out.select("doc_id", "slot", "place").collect()] == [tuple(r) for r in want.select("doc_id", "_slot", "_place").collect()]
