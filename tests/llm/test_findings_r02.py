"""Findings of round 2 on the document operators."""

import numpy as np
import pyarrow as pa

from panelspark.llm import neighbours, repeats


def test_contents_that_share_only_a_short_string_stay_out_of_the_index(monkeypatch):
    """a string of 16 bytes in many documents gave their contents one key, and all of them were indexed."""
    rng = np.random.default_rng(5)
    word = lambda n: bytes(rng.integers(97, 123, n, dtype=np.uint8))
    short, long_ = word(20), word(60)
    texts = [(word(60) + (long_ if k % 10 == 0 else short) + word(60)).decode() for k in range(60)]
    docs = pa.table({"doc_id": pa.array(range(60), pa.int64()), "doc": pa.array(range(60), pa.int64()), "tid": pa.array(range(60), pa.int64()), "text": texts, "grp": pa.array(np.zeros(60), pa.int32())})
    sizes, made = [], repeats.RunLengthIndex.__init__
    monkeypatch.setattr(repeats.RunLengthIndex, "__init__", lambda self, text, size, owner, length: (sizes.append(len(size)), made(self, text, size, owner, length))[1])
    told = repeats.shared_keys(repeats.group_keys(docs, 50, 1))
    found = repeats.stretches(docs, told, 50, 1, 1)
    out = repeats.removed(docs, pa.concat_tables([told, repeats.marked(found, 50)]), 50, 1, 1, False)
    assert sum(sizes) <= 30
    assert [n > 0 for n in out.column("n_removed").to_pylist()] == [k % 10 == 0 and k > 0 for k in range(60)]


def test_window_repeats():
    a, b = np.arange(70, dtype=np.uint8), np.arange(100, 170, dtype=np.uint8)
    c = np.concatenate([b[:10], a[20:], b[:9]])
    text = np.concatenate([a, b, c])
    assert repeats.window_repeats(text, np.array([70, 70, len(c)]), 50).tolist() == [True, False, True]
    assert repeats.window_repeats(text[:0], np.zeros(0, np.int64), 50).tolist() == []


def nearest_by_loops(x, ids, asked, k):
    want = {}
    for q in asked:
        d = np.sqrt(((x - x[q]) ** 2).sum(1))
        want[ids[q]] = sorted((a, i) for a, i in zip(d, ids, strict=True) if i != ids[q])[:k]
    return want


def found(x, ids, asked, k=10):
    rows = pa.table({"vec_id": pa.array(ids), "embedding": pa.array(list(x))})
    got = neighbours.shard_search(None, rows, rows.take(pa.array(asked)), k, 1.0).to_pandas()
    return {q: list(zip(g.score, g.vec_id, strict=True)) for q, g in got.groupby("query_id")}


def test_each_node_of_a_tree_is_met_once(monkeypatch):
    """Growth of op7: queries that took different sides at a node met what is below it apart, so that nodes were met over and over."""
    x, ids, asked = np.random.default_rng(4).normal(size=(4000, 64)), np.arange(4000), list(range(0, 4000, 50))
    trees, met, made, offer = [], [], neighbours.VantageTree.__init__, neighbours.VantageTree._offer
    monkeypatch.setattr(neighbours.VantageTree, "__init__", lambda self, *a: (trees.append(self), made(self, *a))[1])
    monkeypatch.setattr(neighbours.VantageTree, "_offer", lambda self, *a: (met.append(1), offer(self, *a))[1])
    assert found(x, ids, asked) == nearest_by_loops(x, ids, asked, 10)
    assert len(met) <= len(trees[0].nodes)


def test_neighbours_far_from_the_origin():
    """Distances from products of long vectors are rough: the place of a neighbour was taken for sure by a fixed margin."""
    rng = np.random.default_rng(6)
    ids, asked = np.arange(1500), list(range(0, 1500, 50))
    for x in (3e7 + rng.normal(size=(1500, 6)), 1e-9 * rng.normal(size=(1500, 6)), np.where(rng.random((1500, 6)) < 0.3, -0.0, rng.integers(0, 2, (1500, 6)) + 0.0) + np.array([1.0, 0, 0, 0, 0, 0])):
        assert found(x, ids, asked) == nearest_by_loops(x, ids, asked, 10)
