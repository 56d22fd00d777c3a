"""Removal of long repeats by a run-length index: a run-compressed Burrows-Wheeler transform with sampled run ends.

A match of `length` bytes is a repeat where the same bytes also start in a document with a smaller doc_id.

1. Documents are dealt into groups. Every window of `length` bytes has a key: the smallest hash of the 16-byte strings
   inside it. Equal windows have equal keys, and neighbouring windows mostly share theirs, so a document becomes short
   runs of windows with one key. A group sends each key once, and hears which keys another document holds too.
2. The stretches of text under those keys meet by key; a group sends each distinct content once, with the smallest
   document that holds it there. For each batch of contents that share a key with another one the index is built: the
   transform as runs, text positions sampled at the ends of the runs, and runs of rows with the smallest document of their
   first `length` bytes.
3. Each content streams its matching statistics from nothing, from right to left, many in step: a last-to-first step on
   runs where the byte agrees, else a jump to the nearest sampled run end that carries it. Windows whose match is long
   enough and that a smaller document holds are marked.
4. The answers go back to the groups, content by content; there the covered bytes are taken out of every holder.

Common passages: whatever number of documents hold a key or a content, a group sends it once. Null texts are
empty. Rows with the same doc_id do not remove from each other. A null doc_id counts as larger than all others.
Texts shorter than `length` stay whole. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import U, byte_view, grouped, mix, slices

GRAM = 16
MOST = 35  # windows of a run
LAST = (1 << 63) - 1
SEVERAL = -(1 << 63)  # in place of a document


# ---- windows and their keys


def words64(data: np.ndarray) -> np.ndarray:
    """The eight bytes from each position on, as one number."""
    n = len(data) - 7
    out = np.empty(max(n, 0), np.uint64)
    for s in range(min(8, max(n, 0))):
        m = (len(data) - s) // 8
        out[s::8] = data[s : s + 8 * m].view("<u8")[: len(out[s::8])]
    return out


def window_runs(data: np.ndarray, offsets: np.ndarray, length: int):
    """Runs of neighbouring windows with one key: key, start, number of windows, row. At most 35 windows a run."""
    n = len(data)
    none = (np.zeros(0, np.uint64),) + (np.zeros(0, np.int64),) * 3
    if n < length:
        return none
    w = words64(np.ascontiguousarray(data))
    h = w[:-8] * U(0x9E3779B97F4A7C15) + w[8:] * U(0xC2B2AE3D27D4EB4F)
    h ^= h >> U(29)
    h *= U(0xBF58476D1CE4E5B9)
    h >>= U(12)
    h |= U(0x3FF0000000000000)
    m = h.view(np.float64)  # 52 random bits as numbers from 1 to 2, whose order is that of the bits
    span, want = 1, length - GRAM + 1
    while span * 2 <= want:
        m = np.minimum(m[:-span], m[span:])
        span *= 2
    if want > span:
        m = np.minimum(m[: len(m) - (want - span)], m[want - span :])
    last = len(m)
    edge = np.zeros(last + 1, np.int32)  # windows that would cross into the next row
    np.add.at(edge, np.minimum(np.maximum(offsets[:-1], offsets[1:] - length + 1), last), 1)
    np.add.at(edge, np.minimum(offsets[1:], last), -1)
    sound = np.cumsum(edge[:-1]) == 0
    fresh = np.ones(last, bool)
    fresh[1:] = m[1:] != m[:-1]
    fresh[offsets[:-1][offsets[:-1] < last]] = True
    fresh[1:] |= ~sound[:-1]
    starts = np.flatnonzero(fresh & sound)
    stops = np.flatnonzero(sound & np.append(fresh[1:] | ~sound[1:], True)) + 1
    pieces = (stops - starts + MOST - 1) // MOST
    if len(pieces) and pieces.max() > 1:
        at = np.repeat(np.arange(len(starts)), pieces)
        k = np.arange(len(at)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        starts, stops = starts[at] + k * MOST, np.minimum(starts[at] + (k + 1) * MOST, stops[at])
    # smallest hashes crowd near zero: they are mixed, and 48 bits of that are the key
    return mix(m[starts].view(np.uint64)) >> U(16), starts, stops - starts, np.searchsorted(offsets, starts, side="right") - 1


def window_repeats(text: np.ndarray, size: np.ndarray, length: int) -> np.ndarray:
    """For each of many texts of at least `length` bytes, whether one of its windows has the hash of another window."""
    size = size.astype(np.int64)
    windows = size - length + 1
    row = np.repeat(np.arange(len(size)), windows)
    at = np.arange(len(row)) - np.repeat(np.cumsum(windows) - windows, windows) + np.repeat(np.cumsum(size) - size, windows)
    w = words64(text)
    h = np.zeros(max(len(text) - length + 1, 0), np.uint64)
    for k in (*range(0, length - 8, 8), length - 8):
        h = mix(h ^ w[k : k + len(h)]) * U(0x9E3779B97F4A7C15)
    _, place, count = np.unique(h[at], return_inverse=True, return_counts=True)
    out = np.zeros(len(size), bool)
    out[row[count[place] > 1]] = True
    return out


def _bucket(keys: np.ndarray, buckets: int) -> np.ndarray:
    """Ranges of keys, so that sorted keys of a bucket differ by little."""
    return ((keys >> U(16)) * U(buckets) >> U(32)).astype(np.int64)


def _pack(*arrays) -> bytes:
    """Arrays of whole numbers, byte place by byte place, as few places as the largest needs; bytes stay as they are."""
    out = []
    for a in arrays:
        if a.dtype == np.uint8:
            out.append(np.array([len(a), 0], np.int64).tobytes() + a.tobytes())
            continue
        x = np.ascontiguousarray(a.astype("<i8")).view(np.uint8).reshape(-1, 8)
        width = int(np.flatnonzero(x.any(0)).max(initial=-1)) + 1 if len(a) else 0
        out.append(np.array([len(a), width], np.int64).tobytes() + np.ascontiguousarray(x[:, :width].T).tobytes())
    return zstandard.ZstdCompressor(level=3).compress(b"".join(out))


def _unpack(blob: bytes, *kinds) -> list[np.ndarray]:
    raw, at, out = zstandard.ZstdDecompressor().decompress(blob), 0, []
    for kind in kinds:
        n, width = (int(x) for x in np.frombuffer(raw, np.int64, 2, at))
        at += 16
        if kind == np.uint8:
            out.append(np.frombuffer(raw, np.uint8, n, at))
            at += n
            continue
        x = np.zeros((n, 8), np.uint8)
        x[:, :width] = np.frombuffer(raw, np.uint8, n * width, at).reshape(width, n).T
        out.append(x.view("<i8").ravel().astype(kind, copy=False))
        at += n * width
    return out


def _cuts(x: np.ndarray) -> np.ndarray:
    """The starts of the runs of equal values, and the length."""
    return np.concatenate([[0], np.flatnonzero(x[1:] != x[:-1]) + 1, [len(x)]]) if len(x) else np.zeros(1, np.int64)


# ---- what a group of documents sends


class Group:
    """The documents of one group in order, their bytes, and the runs of windows: key, start, number of windows, row."""

    def __init__(self, docs: pa.Table, length: int):
        order = np.lexsort((np.asarray(docs.column("tid")), np.asarray(docs.column("doc"))))
        self.docs = docs.take(pa.array(order))
        self.doc = np.asarray(self.docs.column("doc"))
        self.data, self.off = byte_view(self.docs.column("text"))
        self.length = length
        runs = []
        for i, j in slices(self.off, 1 << 17):
            k, start, n, row = window_runs(self.data[self.off[i] : self.off[j]], self.off[i : j + 1] - self.off[i], length)
            runs.append((k, start + self.off[i], n, row + i))
        self.key, self.start, self.n, self.row = (np.concatenate(x) if runs else np.zeros(0, np.int64) for x in (zip(*runs, strict=True) if runs else [()] * 4))
        self.key = self.key.astype(np.uint64)

    def keys(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Distinct keys, ascending, with the smallest and the largest document of each."""
        order = np.argsort(self.key, kind="stable")
        k, d = self.key[order], self.doc[self.row[order]]
        at = _cuts(k)[:-1]
        return (k[at], np.minimum.reduceat(d, at), np.maximum.reduceat(d, at)) if len(k) else (k, d, d)

    def keep(self, bits: list[tuple[int, bytes]], buckets: int) -> None:
        """Leaves the runs under keys that several documents hold; bits: by bucket, a bit for each distinct key."""
        distinct, place = np.unique(self.key, return_inverse=True)
        shared = np.zeros(len(distinct), bool)
        b = _bucket(distinct, buckets)
        for bucket, blob in bits:
            lo, hi = np.searchsorted(b, [bucket, bucket + 1])
            shared[lo:hi] = np.unpackbits(np.frombuffer(blob, np.uint8), count=hi - lo)
        hit = shared[place]
        self.key, self.start, self.n, self.row = self.key[hit], self.start[hit], self.n[hit], self.row[hit]

    def contents(self) -> None:
        """Numbers the distinct contents of the runs in order of key and hash: `content` of each run, `first` run of each."""
        size = self.n + self.length - 1
        width = -(-(MOST + self.length - 1) // 8) * 8
        h = np.zeros(len(size), np.uint64)
        padded = np.concatenate([self.data, np.zeros(width, np.uint8)])
        for lo in range(0, len(size), 1 << 14):
            z = size[lo : lo + (1 << 14)]
            cell = padded[self.start[lo : lo + (1 << 14), None] + np.arange(width)]
            cell[np.arange(width) >= z[:, None]] = 0
            x = z.astype(np.uint64)
            for word in cell.view(np.uint64).T:
                x = mix(x ^ word) * U(0x9E3779B97F4A7C15) + word
            h[lo : lo + (1 << 14)] = x
        order = np.lexsort((h, self.key))
        new = np.ones(len(order), bool)
        new[1:] = (h[order][1:] != h[order][:-1]) | (self.key[order][1:] != self.key[order][:-1])
        self.content = np.empty(len(order), np.int64)
        self.content[order] = np.cumsum(new) - 1
        self.first = order[new]
        at = np.flatnonzero(new)
        self.holder = np.minimum.reduceat(self.doc[self.row[order]], at) if len(at) else self.doc[:0]


def group_keys(docs: pa.Table, length: int, buckets: int) -> pa.Table:
    """Rows (bucket, grp, blob): the distinct keys of one group, and of each the only document, or that there are several."""
    k, low, high = Group(docs, length).keys()
    low = np.where(low == high, low, SEVERAL)
    b = _bucket(k, buckets)
    cuts, blobs = _cuts(b), []
    for x, y in zip(cuts[:-1], cuts[1:], strict=True):
        used, place = np.unique(low[x:y], return_inverse=True)
        blobs.append(_pack(np.diff(k[x:y], prepend=U(0)), place, used))
    return pa.table({"bucket": pa.array(b[cuts[:-1]], pa.int64()), "grp": pa.array(np.full(len(blobs), docs.column("grp")[0].as_py()), pa.int32()), "blob": pa.array(blobs, pa.binary())})


def shared_keys(table: pa.Table) -> pa.Table:
    """Rows (grp, bucket, kind, blob): for each group, one bit a key: whether at least two documents hold it."""
    parts = [_unpack(b, np.uint64, np.int64, np.int64) for b in table.column("blob").to_pylist()]
    k = np.concatenate([np.cumsum(p[0], dtype=np.uint64) for p in parts])
    doc = np.concatenate([p[2][p[1]] for p in parts])
    order = np.argsort(k, kind="stable")
    at, d = _cuts(k[order])[:-1], doc[order]
    low, high = np.minimum.reduceat(d, at), np.maximum.reduceat(d, at)
    shared = np.empty(len(k), bool)
    shared[order] = np.repeat((low != high) | (low == SEVERAL), np.diff(np.append(at, len(k))))
    ends = np.cumsum([0] + [len(p[0]) for p in parts])
    blobs = [np.packbits(shared[x:y]).tobytes() for x, y in zip(ends[:-1], ends[1:], strict=True)]
    return pa.table({"grp": table.column("grp"), "bucket": table.column("bucket"), "kind": pa.array(np.zeros(len(blobs)), pa.int32()), "blob": pa.array(blobs, pa.binary())})


def _rows(table: pa.Table, kind: int) -> list[tuple[int, bytes]]:
    return sorted((b, blob) for b, k, blob in zip(table.column("bucket").to_pylist(), table.column("kind").to_pylist(), table.column("blob").to_pylist(), strict=True) if k == kind)


def _stretches(docs: pa.Table, told: pa.Table, length: int, buckets: int) -> Group:
    group = Group(docs, length)
    group.keep(_rows(told, 0), buckets)
    group.contents()
    return group


def stretches(docs: pa.Table, told: pa.Table, length: int, buckets: int, batches: int) -> pa.Table:
    """Rows (bucket, grp, blob): the distinct contents of one group under shared keys, each with its smallest document."""
    if not docs.num_rows:
        return pa.table({"bucket": pa.array([], pa.int64()), "grp": pa.array([], pa.int32()), "blob": pa.array([], pa.binary())})
    group = _stretches(docs, told, length, buckets)
    b = _bucket(group.key[group.first], batches)
    start, size = group.start[group.first], group.n[group.first] + length - 1
    cuts, blobs = _cuts(b), []
    for x, y in zip(cuts[:-1], cuts[1:], strict=True):
        z = size[x:y]
        at = np.repeat(start[x:y] - np.concatenate([[0], np.cumsum(z)[:-1]]), z) + np.arange(z.sum())
        used, place = np.unique(group.holder[x:y], return_inverse=True)
        blobs.append(_pack(group.data[at], z.astype(np.uint8), place, used))
    return pa.table({"bucket": pa.array(b[cuts[:-1]], pa.int64()), "grp": pa.array(np.full(len(blobs), docs.column("grp")[0].as_py()), pa.int32()), "blob": pa.array(blobs, pa.binary())})


# ---- the index


class RunStarts:
    """A bit for each row, set where a run begins, and the runs before every 64 rows: the run of any row by counting bits."""

    def __init__(self, starts: np.ndarray, rows: int):
        bits = np.zeros(-(-(rows + 1) // 64) * 64, bool)
        bits[starts] = True
        self.words = np.packbits(bits, bitorder="little").view("<u8")
        self.before = np.concatenate([[0], np.cumsum(np.bitwise_count(self.words), dtype=np.int32)[:-1]]).astype(np.int32)

    def of(self, rows: np.ndarray) -> np.ndarray:
        at = rows >> 6
        mask = U(0xFFFFFFFFFFFFFFFF) >> (63 - (rows & 63)).astype(np.uint64)
        return self.before[at] + np.bitwise_count(self.words[at] & mask).astype(np.int64) - 1

    @property
    def nbytes(self) -> int:
        return self.words.nbytes + self.before.nbytes


class RunLengthIndex:
    """Over short texts of at most 105 bytes: the transform as runs, samples at run ends, and who holds each long match first.

    What is kept beside the texts has one entry a run, of equal symbols in the transform or of rows with one owner, and under
    two bits a row to find runs. The full order of the suffixes lives only while the index is built. `jumps` counts the
    jumps of all statistics.
    """

    def __init__(self, text: np.ndarray, size: np.ndarray, owner: np.ndarray, length: int):
        """text: all bytes in a row; size: of each text; owner: the smallest document that holds each text."""
        n_texts, size = len(size), size.astype(np.int64)
        self.length, self.size = length, size
        total = int(size.sum()) + n_texts
        self.end = np.cumsum(size + 1) - 1  # where each text's terminator is
        self.ends = RunStarts(np.concatenate([[0], self.end + 1]), total)
        self.start = self.end - size
        t = np.zeros(total, np.int64)
        body = np.ones(total, bool)
        body[self.end] = False
        t[body] = text.astype(np.int64) + 1
        which = np.repeat(np.arange(n_texts), size + 1)
        stop = self.end[which]
        # ranks by 7 symbols, then twice as many again and again; each terminator is a symbol of its own
        place = np.arange(total)
        key = np.zeros(total, np.uint64)
        for k in range(7):
            q = np.minimum(place + k, stop)
            key = (key << U(9)) | t[q].astype(np.uint64)
        order = np.argsort(key)
        first = self._first(key[order])
        rank = np.empty(total, np.int64)  # a rank is the row where its set of equal suffixes begins
        rank[order] = first
        rank[self.end] = np.arange(n_texts)
        order[:n_texts] = self.end
        loose = self._repeated(rank[order])  # rows whose suffixes are not told apart yet
        span, most, exact = 7, int(size.max(initial=0)) + 1, None
        while span < most and len(loose):
            if exact is None and span * 2 >= length:
                exact = (rank.copy(), np.minimum(place + length - span, stop))
            who = order[loose]
            key = (rank[who].astype(np.uint64) << U(32)) | rank[np.minimum(who + span, stop[who])].astype(np.uint64)
            again = np.argsort(key)
            order[loose] = who[again]
            rank[who[again]] = loose[self._first(key[again])]
            loose = loose[self._repeated(rank[order[loose]])]
            span *= 2
        if exact is None:  # every suffix was told apart before
            exact = (rank, place)
        rows = len(order)
        before = t[order - 1]
        cut = np.flatnonzero(np.concatenate([[True], before[1:] != before[:-1]])) if rows else np.zeros(0, np.int64)
        self.run = cut
        self.runs = RunStarts(cut, rows)
        self.run_symbol = before[cut]
        width = np.diff(np.append(cut, rows))
        # where a run's rows go: after all smaller symbols and the same symbol of earlier runs
        by_symbol = np.argsort(self.run_symbol, kind="stable")
        goes = np.empty(len(cut), np.int64)
        goes[by_symbol] = np.cumsum(width[by_symbol]) - width[by_symbol]
        self.run_goes = goes
        self.run_end = np.append(cut[1:], rows)[: len(cut)] - 1
        self.sample_first, self.sample_last = order[cut], order[self.run_end]
        self.by_symbol = by_symbol
        self.symbol_key = self.run_symbol[by_symbol] * len(cut) + by_symbol
        # suffixes that agree in `length` symbols, and runs of rows whose sets have one smallest owner
        r, q = exact
        a, b = r[order], r[q[order]]
        apart = np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])) if rows else np.zeros(0, np.int64)
        first = np.minimum.reduceat(owner[which[order]], apart) if rows else owner[:0]
        change = np.flatnonzero(np.concatenate([[True], first[1:] != first[:-1]])) if rows else apart
        self.owner_runs, self.owner = RunStarts(apart[change], rows), first[change]
        self.text = t.astype(np.uint16)
        self.jumps = 0

    @staticmethod
    def _first(s):
        """For sorted values: the place where the run of equal ones begins."""
        new = np.zeros(len(s), np.int64)
        new[1:] = np.where(s[1:] != s[:-1], np.arange(1, len(s)), 0)
        return np.maximum.accumulate(new)

    @staticmethod
    def _repeated(s):
        """For sorted values: the places that have an equal neighbour."""
        same = s[1:] == s[:-1]
        flag = np.zeros(len(s), bool)
        flag[1:] |= same
        flag[:-1] |= same
        return np.flatnonzero(flag)

    def _common(self, a: np.ndarray, b: np.ndarray, most: np.ndarray) -> np.ndarray:
        """Symbols from text positions a and b on that agree, up to most of each; terminators agree with nothing."""
        stop = lambda x: self.end[self.ends.of(x)] - x
        most = np.minimum(most, np.minimum(stop(a), stop(b)))
        out = most.copy()
        for lo in range(0, len(a), 1 << 13):
            part = slice(lo, lo + (1 << 13))
            reach = np.arange(int(most[part].max(initial=0)))
            if len(reach):
                n = len(self.text) - 1
                differ = self.text[np.minimum(a[part, None] + reach, n)] != self.text[np.minimum(b[part, None] + reach, n)]
                out[part] = np.where(differ.any(1), np.minimum(differ.argmax(1), most[part]), most[part])
        return out

    def statistics(self, text: np.ndarray, size: np.ndarray):
        """For each position of many texts, from right to left in step: the length of a longest match and its row.

        Yields (lanes, position, length, row).
        """
        size = size.astype(np.int64)
        first = np.cumsum(size) - size
        lanes = np.argsort(-size, kind="stable")
        q, matched = np.zeros(len(size), np.int64), np.zeros(len(size), np.int64)
        place = np.full(len(size), self.end[0] if len(self.end) else 0)  # the text position of each row q
        for step in range(int(size.max(initial=0))):
            lanes = lanes[: np.searchsorted(-size[lanes], -step, side="left")]
            at = size[lanes] - 1 - step
            symbol = text[first[lanes] + at].astype(np.int64) + 1
            row, where, length = q[lanes], place[lanes], matched[lanes]
            run = self.runs.of(row)
            off = np.flatnonzero(self.run_symbol[run] != symbol)
            if len(off):
                run[off], row[off], where[off], length[off] = self._jump(run[off], where[off], length[off], symbol[off])
            known = length >= 0
            q[lanes] = np.where(known, self.run_goes[run] + row - self.run[run], 0)
            place[lanes] = np.where(known, where - 1, self.end[0])
            matched[lanes] = np.where(known, length + 1, 0)
            yield lanes, at, matched[lanes], q[lanes]

    def _jump(self, run, where, length, symbol):
        """The nearest run ends that carry the wanted symbol, whichever agrees longer with the match so far; length -1 where
        no run carries it."""
        self.jumps += len(run)
        n = len(self.run)
        nxt = np.searchsorted(self.symbol_key, symbol * n + run)
        down, up = np.minimum(nxt, n - 1), np.maximum(nxt - 1, 0)
        has_down = (nxt < n) & (self.run_symbol[self.by_symbol[down]] == symbol)
        has_up = (nxt > 0) & (self.run_symbol[self.by_symbol[up]] == symbol)
        down, up = self.by_symbol[down], self.by_symbol[up]
        a = np.where(has_up, self._common(where, self.sample_last[up], length), -1)
        b = np.where(has_down, self._common(where, self.sample_first[down], length), -1)
        better = a >= b
        return np.where(better, up, down), np.where(better, self.run_end[up], self.run[down]), np.where(better, self.sample_last[up], self.sample_first[down]), np.maximum(a, b)

    def first_owner(self, rows: np.ndarray) -> np.ndarray:
        """The smallest document with the `length` bytes that begin at each row."""
        return self.owner[self.owner_runs.of(rows)]


def marked(table: pa.Table, length: int) -> pa.Table:
    """Rows (grp, bucket, kind, blob): for each content of one bucket, who holds it first, and for those first holders the
    windows that smaller documents hold within other contents."""
    parts = [_unpack(b, np.uint8, np.uint8, np.int64, np.int64) for b in table.column("blob").to_pylist()]
    number: dict[bytes, int] = {}
    same = []
    for raw, size, _, _ in parts:
        whole, ends = raw.tobytes(), np.cumsum(size.astype(np.int64))
        same.append(np.fromiter((number.setdefault(whole[e - z : e], len(number)) for e, z in zip(ends.tolist(), size.tolist(), strict=True)), np.int64, len(size)))
    holder = [p[3][p[2]] for p in parts]
    owner = np.full(len(number), LAST)
    np.minimum.at(owner, np.concatenate(same), np.concatenate(holder))
    text = np.frombuffer(b"".join(number), np.uint8)
    sizes = np.fromiter(map(len, number), np.int64, len(number))
    flag = np.zeros((len(sizes), int(sizes.max()) - length + 1), bool)
    # windows of two contents can only be equal under one key: contents whose key is theirs alone stay out of the index
    key, _, _, row = window_runs(text, np.concatenate([[0], np.cumsum(sizes)]), length)
    _, place, count = np.unique(key, return_inverse=True, return_counts=True)
    some = np.zeros(len(sizes), bool)
    some[row[count[place] > 1]] = True
    # most of these only share a short string: a content none of whose windows has the hash of another window stays out too
    some[np.flatnonzero(some)] = window_repeats(text[np.repeat(some, sizes)], sizes[some], length)
    if some.any():
        some_text, some_sizes, some_owner = text[np.repeat(some, sizes)], sizes[some], owner[some]
        some = np.flatnonzero(some)
        index = RunLengthIndex(some_text, some_sizes, some_owner, length)
        for lanes, at, matched, row in index.statistics(some_text, some_sizes):
            long_ = np.flatnonzero((at + length <= some_sizes[lanes]) & (matched >= length))
            if len(long_):
                who = lanes[long_]
                flag[some[who], at[long_]] = index.first_owner(row[long_]) < some_owner[who]
    blobs = []
    for number_, held in zip(same, holder, strict=True):
        first = owner[number_]
        used, place = np.unique(first, return_inverse=True)
        content, window = np.nonzero(flag[number_] & (first == held)[:, None])
        blobs.append(_pack(place, used, content, window))
    return pa.table({"grp": table.column("grp"), "bucket": table.column("bucket"), "kind": pa.array(np.ones(len(blobs)), pa.int32()), "blob": pa.array(blobs, pa.binary())})


# ---- back to the documents


def removed(docs: pa.Table, told: pa.Table, length: int, buckets: int, batches: int, with_text: bool) -> pa.Table:
    """The documents of one group without the marked bytes."""
    if docs.num_rows:
        group = _stretches(docs, told, length, buckets)
    else:
        group = Group(docs, length)
        group.contents()
    owner, flags = np.full(len(group.first), LAST), []
    b = _bucket(group.key[group.first], batches)
    for bucket, blob in _rows(told, 1):
        place, used, content, window = _unpack(blob, np.int64, np.int64, np.int64, np.int64)
        lo, hi = np.searchsorted(b, [bucket, bucket + 1])
        owner[lo:hi] = used[place]
        flags.append((content + lo, window))
    doc = group.doc[group.row]
    late = doc > owner[group.content]
    lo, hi = [group.start[late]], [group.start[late] + group.n[late] + length - 1]
    if flags:  # first holders lose single windows
        content, window = (np.concatenate(x) for x in zip(*flags, strict=True))
        early = np.flatnonzero(doc == owner[group.content])
        early = early[np.argsort(group.content[early], kind="stable")]
        x, y = (np.searchsorted(group.content[early], content, side=side) for side in ("left", "right"))
        run = early[np.repeat(x - np.concatenate([[0], np.cumsum(y - x)[:-1]]), y - x) + np.arange((y - x).sum())]
        at = group.start[run] + np.repeat(window, y - x)
        lo.append(at)
        hi.append(at + length)
    lo, hi = np.concatenate(lo), np.concatenate(hi)
    n = len(group.data)
    edge = np.bincount(lo, minlength=n + 1) - np.bincount(hi, minlength=n + 1)
    gone = np.cumsum(edge[:n]) > 0
    n_bytes, n_removed, n_spans, sha, kept = [], [], [], [], []
    for x, y in zip(group.off[:-1], group.off[1:], strict=True):
        text, cut = group.data[x:y], gone[x:y]
        rest_bytes = text[~cut].tobytes()
        n_bytes.append(y - x)
        n_removed.append(y - x - len(rest_bytes))
        n_spans.append(int(cut[:1].sum()) + int(np.count_nonzero(cut[1:] & ~cut[:-1])))
        sha.append(hashlib.sha256(rest_bytes).hexdigest())
        kept.append(rest_bytes.decode("utf-8", "ignore") if with_text else None)
    out = {"doc_id": group.docs.column("doc_id"), "n_bytes": pa.array(n_bytes, pa.int64()), "n_removed": pa.array(n_removed, pa.int64()), "n_spans": pa.array(n_spans, pa.int64()), "kept_sha256": pa.array(sha, pa.string())}
    if with_text:
        out["text"] = pa.array(kept, pa.string())
    return pa.table(out)


def without_repeats(docs: DataFrame, length: int = 50, with_text: bool = False, group_bytes: int = 6 << 20, key_bytes: int = 6 << 20, batch_bytes: int = 2 << 20) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans and kept_sha256 of each row of docs(doc_id, text); the kept text on demand."""
    if not 24 <= length <= 70:
        raise ValueError("length must be from 24 to 70")
    here = "panelspark.llm.repeats"
    total = docs.agg(F.coalesce(F.sum(F.octet_length("text").cast("long")), F.lit(0))).first()[0]
    groups, buckets, batches = (max(8, -(-int(x) // y)) for x, y in ((total, group_bytes), (total, key_bytes), (total * 1.2, batch_bytes)))
    rows = docs.select("doc_id", F.coalesce("doc_id", F.lit(LAST)).alias("doc"), F.coalesce("text", F.lit("")).alias("text")).withColumn("tid", F.xxhash64("text"))
    texts = rows.withColumn("grp", F.pmod(F.xxhash64("doc", "tid"), F.lit(groups)).cast("int")).select("doc_id", "doc", "tid", "text", "grp")
    answer = "grp int, bucket long, kind int, blob binary"
    keys = texts.groupBy("grp").applyInArrow(grouped(here, "group_keys", length, buckets), "bucket long, grp int, blob binary")
    shared = keys.groupBy("bucket").applyInArrow(grouped(here, "shared_keys"), answer)
    found = texts.groupBy("grp").cogroup(shared.groupBy("grp")).applyInArrow(grouped(here, "stretches", length, buckets, batches), "bucket long, grp int, blob binary")
    marks = found.groupBy("bucket").applyInArrow(grouped(here, "marked", length), answer)
    kind = "doc_id " + docs.schema["doc_id"].dataType.simpleString() + ", n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", text string" if with_text else "")
    return texts.groupBy("grp").cogroup(shared.unionByName(marks).groupBy("grp")).applyInArrow(grouped(here, "removed", length, buckets, batches, with_text), kind)
