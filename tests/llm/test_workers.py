"""The parts that run inside tasks, without Spark."""

import random

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import pytest

import brute
from panelspark.llm import jaccard, language, media, mixing, neighbours, pieces, queries, repeats, token_counts, toxicity
from panelspark.llm.components import Forest

MODEL = queries.tokenizer("piece_bpe_32k.model")
ODD = ["", " ", "  a  b", "x" * 300, "a\n\n\tb \r\n c", "日本語 テスト 한국어", "é́ \x00 \U0001f600 ▁ <s> </s>", "word " * 500, "▁▁", "a" * 50 + "\n" + "b" * 50]


def test_token_counts_equal_the_library():
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    counter = token_counts.UnitCounter(MODEL)
    rng = random.Random(3)
    texts = ODD + ["".join(rng.choice(" ab.\nthe é€") for _ in range(rng.randrange(400))) for _ in range(60)]
    want = [len(x) for x in library.encode(texts, num_threads=1)]
    assert [counter.count(t) for t in texts] == want
    for chunk, overlap in ((16, 2), (40, 8), (100, 30)):
        assert [counter.count_long(t, chunk, overlap)[0] for t in texts] == want


def test_pieces_find_the_best_score_and_decode():
    c = pieces.PieceCodec(MODEL)
    from sentencepiece import sentencepiece_model_pb2 as pb

    m = pb.ModelProto()
    m.ParseFromString(open(MODEL, "rb").read())
    score = {p.piece: p.score for p in m.pieces if p.type == 1}
    for t in [*ODD, "the quick thtionshing of 12345", "Ünïcode straße"]:
        ids = list(c.encode(t))
        assert c.decode(ids) == t.replace("▁", " ")
        for u in c.unit.findall(" " + t)[:20] if t else []:
            u = u.replace(" ", "▁")[:40]
            got, run = 0.0, 0
            for i in c.best(u):  # bytes of one character count once, at the fallback's score
                if i in c.byte_of:
                    run += (c.byte_of[i] & 0xC0) != 0x80
                else:
                    got += score[c.pieces[i]]
            assert got + run * c.worst == pytest.approx(brute.best_score(u, score, c.worst))


def test_pieces_equal_the_library():
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    c = pieces.PieceCodec(MODEL)
    rng = random.Random(5)
    texts = [*ODD, "the quick thtionshing of 12345", "Ünïcode straße", "▁" * 37 + "a" + " " * 21, "unseparated" * 400]
    texts += ["".join(rng.choice("  abehinorst.\n▁é€") for _ in range(rng.randrange(400))) for _ in range(200)]
    assert [c.pieces[i] for i in c.encode("the")] == ["▁the"]
    for t in texts:
        assert c.encode(t).tolist() == library.encode(t), t


def test_run_length_index_and_statistics():
    rng = np.random.default_rng(3)
    for trial in range(20):
        length = (24, 50)[trial % 2]
        base = bytes(rng.integers(97, (99, 120)[trial % 3 == 0], 400, dtype=np.uint8))
        segs = list({base[a : a + int(rng.integers(length, length + 35))] for a in rng.integers(0, 300, int(rng.integers(1, 25)))})
        owner = rng.integers(0, 9, len(segs))
        text, size = np.frombuffer(b"".join(segs), np.uint8), np.array([len(s) for s in segs])
        index = repeats.RunLengthIndex(text, size, owner, length)
        for lanes, at, matched, row in index.statistics(text, size):
            for a, b, m, r in zip(lanes, at, matched, row, strict=True):
                if b + length <= size[a]:
                    gram = segs[a][b : b + length]
                    assert m >= length
                    assert index.first_owner(np.array([r]))[0] == min(o for s, o in zip(segs, owner, strict=True) if gram in s)
        queries_ = [bytes(rng.integers(97, 99, 20, dtype=np.uint8)) + base[5:30]]
        qt, qz = np.frombuffer(b"".join(queries_), np.uint8), np.array([len(x) for x in queries_])
        for lanes, at, matched, _ in index.statistics(qt, qz):
            for a, b, m in zip(lanes, at, matched, strict=True):
                want = 0
                while b + want < len(queries_[a]) and any(queries_[a][b : b + want + 1] in s for s in segs):
                    want += 1
                assert want == m


def test_index_jumps_and_its_memory_follows_runs():
    rng = np.random.default_rng(6)
    base = bytes(rng.integers(97, 123, 5000, dtype=np.uint8))
    sizes = []
    for copies in (2, 40):
        segs = [base[a : a + 84] for a in range(0, 4900, 70) for _ in range(copies)]
        segs = [s[:40] + bytes([65 + k % copies % 26]) + s[41:] if k % copies else s for k, s in enumerate(segs)]
        text, size = np.frombuffer(b"".join(segs), np.uint8), np.array([len(s) for s in segs])
        index = repeats.RunLengthIndex(text, size, np.arange(len(segs)) // copies, 50)
        assert sum(len(lanes) for lanes, *_ in index.statistics(text, size)) == len(text)
        assert index.jumps > len(segs)
        kept = sum(x.nbytes for k, x in vars(index).items() if isinstance(x, np.ndarray) and k not in ("text", "size", "end", "start"))
        assert kept < 100 * (len(index.run) + len(index.owner))
        assert index.runs.nbytes + index.owner_runs.nbytes < len(index.text)
        sizes.append((len(text), len(index.run)))
    assert sizes[1][0] == 20 * sizes[0][0] and sizes[1][1] < 7 * sizes[0][1]  # the text grows, the runs hardly do


def test_groups_send_a_common_passage_once():
    rng = np.random.default_rng(3)
    letters = lambda n: bytes(rng.integers(97, 123, n, dtype=np.uint8)).decode()
    passage = letters(300)
    texts = [letters(80) + passage + letters(60) for _ in range(200)]
    docs = pa.table({"doc_id": pa.array(range(200)), "doc": pa.array(range(200)), "tid": pa.array(range(200)), "text": pa.array(texts), "grp": pa.array([0] * 200, pa.int32())})
    keys = repeats.group_keys(docs, 50, 1)
    told = repeats.shared_keys(keys)
    found = repeats.stretches(docs, told, 50, 1, 1)
    sent, size, _, holder = repeats._unpack(found.column("blob")[0].as_py(), np.uint8, np.uint8, np.int64, np.int64)
    group = repeats._stretches(docs, told, 50, 1)
    assert len(group.key) > 2500 and len(size) < 1000  # runs of windows under shared keys, and what is sent: ends differ, the inside is one
    assert set(holder.tolist()) >= {0} and len(sent) == size.astype(int).sum()
    out = repeats.removed(docs, pa.concat_tables([told, repeats.marked(found, 50)]), 50, 1, 1, True)
    want = brute.without_repeats(list(enumerate(texts)), 50)
    assert sorted(zip(*(out.column(c).to_pylist() for c in ("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")), strict=True)) == want


def test_window_keys_depend_on_content_only():
    rng = np.random.default_rng(1)
    text = rng.integers(97, 101, 400, dtype=np.uint8)
    keys = []
    for shift in (0, 7, 93):
        t = np.concatenate([rng.integers(97, 101, shift, dtype=np.uint8), text])
        k, s, n, _ = repeats.window_runs(t, np.array([0, len(t)]), 50)
        full = np.repeat(k, n)
        at = np.concatenate([np.arange(a, a + b) for a, b in zip(s, n, strict=True)])
        assert (at == np.arange(len(t) - 49)).all()
        keys.append(full[shift:])
    assert (keys[0] == keys[1]).all() and (keys[0] == keys[2]).all()


def near_sets(rng, top, trials):
    """Random sets, each with one that may or may not link with it."""
    out = []
    for trial in range(trials):
        n = int(rng.integers(3, 60)) if trial % 2 else int(rng.integers(60, 500))
        a = np.unique(rng.integers(0, 2**64, n, dtype=np.uint64))
        d = n * (100 - top) // (100 + top) + int(rng.integers(0, 2))
        out += [a, np.unique(np.concatenate([a[d:], rng.integers(0, 2**64, int(rng.integers(0, d + 1)), dtype=np.uint64)]))]
    return out


def linked(a, b, top):
    i = len(np.intersect1d(a, b))
    return 100 * i >= top * (len(a) + len(b) - i)


@pytest.mark.parametrize("top", [80, 90])
def test_linked_sets_share_a_prefix_column(top):
    rng = np.random.default_rng(5)
    sets = near_sets(rng, top, 300)
    names = rng.permutation(len(sets)) + 1
    parts = [pa.table({"class": pa.array(names[p::3]), "part": pa.array([p] * len(names[p::3]), pa.int64()), "items": pa.array([s.tobytes() for s in sets[p::3]])}) for p in range(3)]
    counted = pa.concat_tables([jaccard.part_columns(t, 7) for t in parts])
    group = lambda t, key: [t.filter(pa.compute.equal(t.column(key), k)) for k in sorted(set(t.column(key).to_pylist()))]
    totals = pa.concat_tables([jaccard.column_totals(t) for t in group(counted, "bucket")])
    found = pa.concat_tables([jaccard.prefixes(t, totals.filter(pa.compute.equal(totals.column("part"), p)), top, 100, 7) for p, t in enumerate(parts)])
    links = [(u, v) for u, v in zip(found.column("u").to_pylist(), found.column("v").to_pylist(), strict=True) if u is not None]
    for t in group(found.filter(pa.compute.is_valid(found.column("blob"))), "bucket"):
        made = jaccard.chained(t, top, 100)
        links += zip(made.column("u").to_pylist(), made.column("v").to_pylist(), strict=True)
    forest = Forest()
    for u, v in links:
        forest.join(u, v)
    kept, expected = set(found.column("class").to_pylist()), 0
    for k in range(0, len(sets), 2):
        if linked(sets[k], sets[k + 1], top) and len(sets[k]):
            expected += 1
            assert forest.find(int(names[k])) == forest.find(int(names[k + 1])) and {int(names[k]), int(names[k + 1])} <= kept
    assert 100 < expected < 300


def test_columns_of_one_class_are_counted_from_below():
    texts = ["a b c d e f g", "a b c d x y z", "a b c d e f g", None, "", "q r"]
    batch = pa.RecordBatch.from_arrays([pa.array(texts)], ["text"])
    sets = {jaccard.digest(s): s for _, s in jaccard.doc_sets(pa.array(texts), 3) if len(s)}
    for share in (256, 100):
        rows = [b for part in ([batch], [batch.slice(2)]) for b in jaccard.columns_of(part, 3, share, 2)]
        table = pa.Table.from_batches(rows)
        back = [jaccard.own_columns(table.filter(pa.compute.equal(table.column("bucket"), b)), 3) for b in sorted(set(table.column("bucket").to_pylist()))]
        both = pa.concat_tables(back)
        got = {}
        for p in sorted(set(both.column("part").to_pylist())):
            got |= dict(zip(*jaccard.own_totals(both.filter(pa.compute.equal(both.column("part"), p))).to_pydict().values(), strict=True))
        for c, s in sets.items():
            others = [x for d, x in sets.items() if d != c]
            mine = [x for x in s if not any(x in o for o in others) and int(x) & 255 < share]
            assert got.get(c, 0) == len(mine)


def test_products_count_overlaps():
    rng = np.random.default_rng(7)
    for trial in range(12):
        base = rng.integers(0, 2**64, 300, dtype=np.uint64)
        sets = [np.unique(rng.choice(base, int(rng.integers(0, 90)))) for _ in range(int(rng.integers(1, 90)))]
        got = jaccard.overlaps(sets, (4, 16, 1000, 1)[trial % 4], 50)
        want = [[len(np.intersect1d(a, b)) for b in sets] for a in sets]
        off = ~np.eye(len(sets), dtype=bool)
        assert (got[off] == np.array(want)[off]).all()


def test_packed_arrays_round_trip():
    rng = np.random.default_rng(0)
    k, c = np.sort(rng.integers(0, 2**64, 1000, dtype=np.uint64)), rng.integers(-(2**63), 2**63, 1000)
    a, b = jaccard.unpack(jaccard.pack(k, c))
    assert (a == k).all() and (b == c).all() and len(jaccard.unpack(jaccard.pack(k[:0], c[:0]))[0]) == 0


def test_forest():
    f = Forest()
    for a, b in ((5, 3), (9, 5), (2, 1), (1, 2)):
        f.join(a, b)
    assert sorted(zip(*map(list, f.links()), strict=True)) == [(2, 1), (5, 3), (9, 3)]


def test_schedule_stays_within_a_block():
    for weights in ({"a": 1, "b": 1}, {"a": 2, "b": 3, "c": 1, "(rest)": 8}, {"a": 7, "b": 1, "c": 5}, {"a": 1}):
        plan = sorted(mixing.period_schedule(weights), key=lambda r: r[4])
        period = sum(weights.values())
        assert [r[4] for r in plan] == list(range(period))
        done = dict.fromkeys(weights, 0)
        for s, j, release, deadline, slot in plan:
            assert release <= slot < deadline and j == done[s]
            done[s] += 1
            for t, w in weights.items():
                assert abs(done[t] - w * (slot + 1) / period) < 1


def test_media_round_trip_and_carving():
    for raw in (b"", b"abc", bytes(range(256)) * 5, b"RIFF" * 300, b"GIF89a" + b"x" * 600):
        payload = raw + b"\xff" * (-len(raw) % 576 or (576 if not raw else 0))
        back, found = media.read_back(media.stored(payload))
        assert back == payload and found[0][0] == "wav"
    gif = b"GIF89a\x01\x00\x01\x00\x00\x00\x00,\x00\x00\x00\x00\x01\x00\x01\x00\x00\x02\x02D\x01\x00;"
    import gzip
    import struct
    import zlib

    chunk = lambda n, d: struct.pack(">I", len(d)) + n + d + struct.pack(">I", zlib.crc32(n + d))
    png = b"\x89PNG\r\n\x1a\n" + chunk(b"IHDR", b"\0" * 13) + chunk(b"IEND", b"")
    gz = gzip.compress(b"hello" * 100)
    inner = b"noise" + gif + b"more" + png + gz + b"tail"
    assert [(k, a, e) for k, a, e, _ in media.sniff(inner)] == [("gif", 5, 5 + len(gif)), ("png", 9 + len(gif), 9 + len(gif) + len(png)), ("gzip", 9 + len(gif) + len(png), 9 + len(gif) + len(png) + len(gz))]
    assert media.sniff(png[:-1]) == [] and media.sniff(b"BM" + b"\0" * 60) == []


def test_jpeg_may_end_with_the_value():
    jpeg = b"\xff\xd8\xff\xe0\x00\x04ab\xff\xda\x00\x03\x01scan\xff\x00\xff\xd0data\xff\xd9"
    for before, after in ((b"", b""), (b"noise", b""), (b"noise", b"tail")):
        assert [(k, a, e) for k, a, e, _ in media.sniff(before + jpeg + after)] == [("jpeg", len(before), len(before) + len(jpeg))]
    assert media.sniff(jpeg[:-1]) == [] and media.sniff(jpeg[:-2]) == [] and media.sniff(jpeg[:-2] + b"\xff\xe0") == []


def test_trees_are_exact_with_factor_one():
    rng = np.random.default_rng(2)
    x = np.round(rng.normal(size=(700, 6)), 1)
    x[100:300] = x[0]
    rows = pa.table({"vec_id": pa.array(np.arange(700)), "embedding": pa.array(list(x))})
    asked = rows.take(pa.array(range(0, 700, 50)))
    got = neighbours.shard_search(None, rows, asked, 10, 1.0).to_pandas()
    for q, g in got.groupby("query_id"):
        d = np.sqrt(((x - x[q]) ** 2).sum(1))
        want = sorted((a, i) for i, a in enumerate(d) if i != q)[:10]
        assert [(s, v) for s, v in zip(g.score, g.vec_id, strict=True)] == want


def test_smaller_factors_prune_more():
    rng = np.random.default_rng(8)
    x = rng.normal(size=(40, 8))[rng.integers(0, 40, 3000)] + 0.02 * rng.normal(size=(3000, 8))  # tight groups
    q = x[::60]
    done = [neighbours.recall_and_work(x, q, 10, f) for f in (1.0, 0.5, 0.1)]
    assert done[0][0] == 1.0 and done[1][0] >= 0.9
    assert 0.5 > done[0][1] > done[1][1] > done[2][1]
    noise = rng.normal(size=(2000, 64))
    done = [neighbours.recall_and_work(noise, noise[::40], 10, f) for f in (1.0, 0.2, 0.1)]
    assert done[0][0] == 1.0 and done[0][0] >= done[1][0] >= done[2][0] and done[2][1] < done[0][1]


def plain_votes(rows, names, side_of, text_vector):
    """One-versus-one machines in plain loops: votes by pairs, then sums of margins, then names."""
    votes, sums = dict.fromkeys(names, 0), dict.fromkeys(names, 0.0)
    for n, a in enumerate(names):
        for b in names[n + 1 :]:
            mine = [(side_of(lang) == a, v) for lang, v in rows if side_of(lang) in (a, b)]
            sign = np.array([1.0 if s else -1.0 for s, _ in mine])
            w = language.linear_svm([(np.flatnonzero(v), v[np.flatnonzero(v)]) for _, v in mine], sign)
            m = float(w[:-1] @ text_vector + w[-1])
            votes[a] += m > 0
            votes[b] += m < 0
            sums[a] += m
            sums[b] -= m
    return max(names, key=lambda x: (votes[x], sums[x], x))


def plain_vector(text):
    """Shares of byte n-grams, one at a time."""
    data = np.frombuffer(text.lower().encode(), np.uint8)
    v = np.zeros(1 << language.BITS)
    for order in language.ORDERS:
        for k in range(len(data) - order + 1):
            v[language.codes(data[k : k + order], order)[0]] += 1
    return v / (np.linalg.norm(v) or 1.0)


def test_language_equals_plain_votes():
    rng = random.Random(9)
    vocabulary = {"en": "the of and with house".split(), "de": "der und mit haus nicht".split(), "nl": "het en met huis niet".split(), "fr": "les des que avec maison".split(), "es": "los que con casa una".split()}
    texts = [(lang, " ".join(rng.choice(words) for _ in range(12))) for lang, words in vocabulary.items() for _ in range(8)]
    model = language.fit([(lang, *language.gram_shares(np.frombuffer(t.encode(), np.uint8))) for lang, t in texts])
    rows = [(lang, plain_vector(t)) for lang, t in texts]
    asked = [" ".join(rng.choice(vocabulary[lang] + vocabulary[rng.choice(list(vocabulary))]) for _ in range(9)) for lang in list(vocabulary) * 3] + ["THE HOUSE", "zzz"]
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(asked))), pa.array(asked), pa.array([True] * len(asked))], ["doc_id", "text", "has_letter"])
    got = next(language.predicted([batch], model)).column(1).to_pylist()
    family = language.FAMILY
    for t, lang in zip(asked, got, strict=True):
        v = plain_vector(t)
        f = plain_votes(rows, sorted({family[x] for x in vocabulary}), family.get, v)
        members = sorted(x for x in vocabulary if family[x] == f)
        assert lang == plain_votes([r for r in rows if family[r[0]] == f], members, lambda x: x, v)
    alone = pa.RecordBatch.from_arrays([pa.array(range(5)), pa.array(["the house of the", "der und nicht", "het huis niet", "les maison avec des", "los casa una"]), pa.array([True] * 5)], ["doc_id", "text", "has_letter"])
    assert next(language.predicted([alone], model)).column(1).to_pylist() == ["en", "de", "nl", "fr", "es"]


def test_svm_separates_and_ties_are_stable():
    def sample(alphabet, n):
        rng = np.random.default_rng(n)
        return [language.gram_shares(rng.choice(np.frombuffer(alphabet, np.uint8), 200)) for _ in range(12)]

    rows = [(lang, a, s) for lang, alpha, n in (("en", b"the and", 1), ("de", b"der und", 2), ("fr", b"les que", 3), ("es", b"los ano", 4)) for a, s in sample(alpha, n)]
    model = language.fit(rows)
    assert sorted(model["families"]) == ["germanic", "romance"]
    texts = pa.array(["the and the", "der und der", None, "12 34", ""])
    batch = pa.RecordBatch.from_arrays([pa.array(range(5)), texts, pa.array([True, True, False, False, False])], ["doc_id", "text", "has_letter"])
    out = next(language.predicted([batch], model)).to_pydict()
    assert out["lang_pred"][2:] == ["und"] * 3 and all(0 <= s <= 1 for s in out["score"])
    assert language.fit([])["families"] == {}


def plain_proximal(rows, epochs, l1, alpha=1.0, beta=1.0):
    """Follow the regularised leader, one coordinate at a time."""
    import math

    z, n = {}, {}
    bias = "bias"

    def weight(k):
        pull = 0.0 if k == bias else l1
        x = z.get(k, 0.0)
        return 0.0 if abs(x) <= pull else -(x - math.copysign(pull, x)) / ((beta + math.sqrt(n.get(k, 0.0))) / alpha)

    order = np.random.default_rng(11)
    for _ in range(epochs):
        for i in order.permutation(len(rows)):
            label, features = rows[i]
            at = [*features, bias]
            w = {k: weight(k) for k in at}
            g = 1 / (1 + math.exp(-max(-35, min(35, sum(w.values()))))) - label
            for k in at:
                before = n.get(k, 0.0)
                z[k] = z.get(k, 0.0) + g - (math.sqrt(before + g * g) - math.sqrt(before)) / alpha * w[k]
                n[k] = before + g * g
    return {k: weight(k) for k in z}


def test_toxicity_learner_equals_a_plain_one():
    rng = random.Random(4)
    rows = [(int(k % 5 == 0), sorted({rng.randrange(60) for _ in range(8)} | ({99} if k % 5 == 0 else set()))) for k in range(120)]
    model = toxicity.fit([(label, np.array(f)) for label, f in rows])
    want = plain_proximal(rows, 4, float(np.clip(sum(r[0] for r in rows) / 20, 1.5, 10.0)))
    got = dict(zip(model["at"].tolist(), model["w"].tolist(), strict=True))
    assert got == pytest.approx({k: w for k, w in want.items() if k != "bias" and w}) and model["bias"] == pytest.approx(want["bias"])
    assert got[99] > 1


def test_toxicity_features_equal_plain_ones():
    def plain(text):
        words = "".join(c if c.isalnum() or c == "'" else " " for c in text.lower()).split()
        pairs = [(a, b, g) for g in (1, 2) for a, b in zip(words, words[g:], strict=False)]
        return len(set(words)) + len(set(pairs))

    for text in ("You, you are AWFUL. you are!", "a b a b a b", "", "one", "it's  a 'test' of 2 words-in-one"):
        b = np.frombuffer(text.encode(), np.uint8)
        assert len(np.unique(toxicity.feature_ids(b, np.array([0, len(b)]))[0])) == plain(text)


def test_toxicity_learns_sparse_weights():
    rng = random.Random(1)
    words = [f"w{k}" for k in range(200)]
    rows, texts = [], []
    for k in range(400):
        t = " ".join(rng.choice(words) for _ in range(40)) + (" awful" if k % 4 == 0 else "")
        b = np.frombuffer(t.encode(), np.uint8)
        rows.append((int(k % 4 == 0), np.unique(toxicity.feature_ids(b, np.array([0, len(b)]))[0])))
        texts.append(t)
    model = toxicity.fit(rows)
    batch = pa.RecordBatch.from_arrays([pa.array(range(4)), pa.array(["you are AWFUL.", "w1 w2 w3", "", None])], ["doc_id", "text"])
    out = next(toxicity.scored([batch], model, 0.3)).to_pydict()
    assert out["predicted"][:2] == [1, 0] and out["score"][2] == out["score"][3]
    assert len(model["at"]) < 2000
    assert next(toxicity.scored([batch], toxicity.fit([]), 0.3)).to_pydict()["score"] == [0.0] * 4
