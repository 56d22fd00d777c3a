"""Subword encoding and decoding, by the rule of the model: merges by rank, or the greatest sum of scores.

A model of merges (type BPE; its scores are minus the rank) starts from single characters and always joins the adjacent
pair whose piece has the best score, the leftmost among equals, until no pair is a piece. A heap holds the pairs of
long units; short ones are scanned.

For a model of scores, an Aho-Corasick automaton over the pieces drives a one-pass Viterbi search. The automaton reports, at each end position, every piece that ends there by following its output links; each one relaxes
the best score of that position, so one pass over the text finds the segmentation with the greatest sum of scores.
A character that no piece covers falls back to its UTF-8 bytes at a score below all pieces. Among equal scores the
longer last piece wins, as in the public library's search.

Where no piece holds a word mark after another character, no merge crosses the start of a unit and the best segmentation
of a text is that of its units one by one, so each distinct unit is searched once and kept in a bounded cache. Scores
are those of the model file.

Null and empty texts have no pieces. Decoding gives back the text, with a literal word mark read as a space. Texts
of any length take memory in proportion to themselves. Repeated rows give repeated results.
"""

from __future__ import annotations

import re
from functools import cached_property
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_view, shipped, slices, texts

MARK = "▁"
CACHE = 200_000
SHORT = 40
PIECE = 1 << 20
NEVER = float("inf")


class _Units(dict):
    """The ids of units that were met. The newest CACHE of them, and the CACHE before those; what is met again moves to the
    newest. Long units are not kept."""

    def __init__(self, search, kind):
        self.search, self.kind, self.before = search, kind, {}

    def __missing__(self, unit: str) -> bytes:
        ids = self.before.get(unit)
        if ids is None:
            ids = np.array(self.search(unit.replace(" ", MARK)), self.kind).tobytes()
        if len(unit) <= 4 * SHORT:
            if len(self) >= CACHE:
                self.before = dict(self)
                self.clear()
            self[unit] = ids
        return ids


class PieceCodec:
    def __init__(self, path: str):
        from sentencepiece import sentencepiece_model_pb2 as pb

        model = pb.ModelProto()
        with open(path, "rb") as f:
            model.ParseFromString(f.read())
        self.prefix = MARK if model.normalizer_spec.add_dummy_prefix else ""
        if model.normalizer_spec.name != "identity" or model.normalizer_spec.remove_extra_whitespaces:
            raise ValueError("only models with the identity normaliser are supported")
        self.pieces = [p.piece for p in model.pieces]
        self.kind = np.uint16 if len(self.pieces) < 1 << 16 else np.uint32  # as the cache keeps ids
        normal = [(i, p.piece, p.score) for i, p in enumerate(model.pieces) if p.type == 1]
        self.byte_ids = {int(p.piece[3:5], 16): i for i, p in enumerate(model.pieces) if p.type == 6}
        self.byte_of = {i: b for b, i in self.byte_ids.items()}
        self.unknown = next(i for i, p in enumerate(model.pieces) if p.type == 2)
        self.worst = min(s for _, _, s in normal) - 10.0
        self.normal = normal
        kind = model.trainer_spec.model_type
        if kind not in (1, 2) or any(p.type in (4, 5) for p in model.pieces):
            raise ValueError("only models of scores or merges without user-defined or unused pieces are supported")
        self.rank = {p: -s for _, p, s in normal}.get
        self.ids = {p: i for i, p, _ in normal}
        self.search = self.merged if kind == 2 else self.best
        held = [p for _, p, _ in normal]
        decomposes = not any(MARK in p.lstrip(MARK) for p in held)
        alone = "\n\t\r" if not any(c in p for p in held for c in "\n\t\r") else ""
        # units are cut from the text with plain spaces for word marks: most are then short strings of one byte a letter
        self.unit = re.compile((f"[{alone}]+| *[^ {alone}]+| +" if alone else " *[^ ]+| +") if decomposes else r"[\s\S]+")
        self.cache = _Units(self.search, self.kind)

    @cached_property
    def automaton(self):
        """Over all pieces; only the search by scores needs it."""
        import ahocorasick

        out = ahocorasick.Automaton()
        for i, piece, score in self.normal:
            out.add_word(piece, (len(piece), score, i))
        out.make_automaton()
        return out

    def best(self, unit: str) -> list[int]:
        """The ids of the segmentation with the greatest score."""
        n = len(unit)
        score, back, last, filled = [0.0] * (n + 1), [0] * (n + 1), [-1] * (n + 1), 0
        worst = self.worst
        for end, (size, s, i) in self.automaton.iter(unit):
            end += 1
            while filled < end:  # the fallback is the first offer at each position
                filled += 1
                score[filled], back[filled] = score[filled - 1] + worst, filled - 1
            x = score[end - size] + s
            if x > score[end]:
                score[end], back[end], last[end] = x, end - size, i
        while filled < n:
            filled += 1
            score[filled], back[filled] = score[filled - 1] + worst, filled - 1
        out, at = [], n
        while at:
            if last[at] >= 0:
                out.append(last[at])
            else:
                raw = unit[at - 1].encode()
                out.extend(self.byte_ids.get(b, self.unknown) for b in reversed(raw))
            at = back[at]
        out.reverse()
        return out

    def merged(self, unit: str) -> list[int]:
        """The ids that the merges end with."""
        rank, ids = self.rank, self.ids
        part = list(unit) if len(unit) <= SHORT else self.heaped(unit)
        ranks = [rank(a + b, NEVER) for a, b in zip(part, part[1:])] if len(unit) <= SHORT else []
        while ranks:
            best = min(ranks)
            if best == NEVER:
                break
            k = ranks.index(best)
            joined = part[k] + part[k + 1]
            part[k : k + 2] = (joined,)
            del ranks[k]
            if k:
                ranks[k - 1] = rank(part[k - 1] + joined, NEVER)
            if k < len(ranks):
                ranks[k] = rank(joined + part[k + 1], NEVER)
        out = list(map(ids.get, part))
        if None in out:
            out = []
            for p in part:
                if p in ids:
                    out.append(ids[p])
                else:
                    out.extend(self.byte_ids.get(b, self.unknown) for b in p.encode())
        return out

    def heaped(self, unit: str) -> list[str]:
        """The parts of a long unit after all merges, in n log n steps."""
        part, n, rank = list(unit), len(unit), self.rank
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(found, k, 2) for k in range(n - 1) if (found := rank(unit[k : k + 2])) is not None]
        heapify(heap)
        while heap:
            _, k, size = heappop(heap)
            right = after[k]
            if not part[k] or right == n or len(part[k]) + len(part[right]) != size:
                continue  # one of the two has been merged since
            part[k] += part[right]
            part[right] = ""
            after[k] = after[right]
            if after[k] < n:
                before[after[k]] = k
            for a, b in ((before[k], k), (k, after[k])):
                if a >= 0 and b < n and (found := rank(part[a] + part[b])) is not None:
                    heappush(heap, (found, a, len(part[a]) + len(part[b])))
        return [p for p in part if p]

    def encode(self, text: str) -> np.ndarray:
        if not text:
            return np.zeros(0, np.int32)
        text = (self.prefix + text).replace(MARK, " ")
        if len(text) <= PIECE:
            return np.frombuffer(self.joined(self.unit.findall(text)), self.kind).astype(np.int32)
        parts, units = [], []
        for m in self.unit.finditer(text):  # a long text's units are never held all at once
            units.append(m.group())
            if len(units) >= PIECE // 8:
                parts.append(self.joined(units))
                units = []
        return np.frombuffer(b"".join([*parts, self.joined(units)]), self.kind).astype(np.int32)

    def joined(self, units: list[str]) -> bytes:
        """The ids of units, from the cache or searched."""
        return b"".join(map(self.cache.__getitem__, units))

    def decode(self, ids) -> str:
        ids = ids if isinstance(ids, list) else list(ids)
        out, raw = [], bytearray()
        byte_of, pieces = self.byte_of, self.pieces
        if byte_of.keys().isdisjoint(ids):
            text = "".join(map(pieces.__getitem__, ids))
        else:
            for i in ids:
                if i in byte_of:
                    raw.append(byte_of[i])
                    continue
                if raw:
                    out.append(raw.decode("utf-8", "replace"))
                    raw = bytearray()
                out.append(pieces[i])
            out.append(raw.decode("utf-8", "replace"))
            text = "".join(out)
        text = text.replace(MARK, " ")
        return text[1:] if self.prefix and text.startswith(" ") else text


_CODECS: dict[str, PieceCodec] = {}


def codec(path: str) -> PieceCodec:
    if path not in _CODECS:
        _CODECS[path] = PieceCodec(path)
    return _CODECS[path]


def encoded(batches, path: str, check: bool, most: int = 1 << 21):
    """Batches come back in slices of some megabytes of text, so that ids of a whole batch are never held."""
    c = codec(path)
    for whole in batches:
        _, off = byte_view(whole.column(1))
        for i, j in slices(off, most):
            batch = whole.slice(i, j - i)
            ids, same = [], []
            for t in texts(batch.column(1)):
                found = c.encode(t)
                ids.append(found)
                same.append(c.decode(found.tolist()) == t.replace(MARK, " ") if check else None)
            sizes = np.cumsum([0, *map(len, ids)]).astype(np.int32)
            flat = pa.array(np.concatenate(ids), pa.int32())
            kept = range(2, batch.num_columns)
            columns = [batch.column(0), pa.array(np.diff(sizes).astype(np.int64)), pa.ListArray.from_arrays(pa.array(sizes), flat), pa.array(same, pa.bool_()), *(batch.column(k) for k in kept)]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_pieces", "ids", "round_trip", *(batch.schema.names[k] for k in kept)])


def decoded(batches, path: str):
    c = codec(path)
    for batch in batches:
        out = [None if ids is None else c.decode(ids) for ids in batch.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], ["doc_id", "text"])


def encode(docs: DataFrame, model_path: str, check: bool = True, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, n_pieces, ids and round_trip of each row of docs(doc_id, text), and the columns of `keep`. Narrow.

    round_trip: decoding gave back the text, a literal word mark as a space (such a mark cannot come back)."""
    rows = docs.select("doc_id", "text", *keep)
    kept = "".join(f", `{c}` {rows.schema[c].dataType.simpleString()}" for c in keep)
    return rows.mapInArrow(shipped("panelspark.llm.pieces", "encoded", model_path, check), f"doc_id long, n_pieces long, ids array<int>, round_trip boolean{kept}")


def decode(rows: DataFrame, model_path: str) -> DataFrame:
    """doc_id and text of each row of rows(doc_id, ids)."""
    return rows.select("doc_id", F.col("ids").cast("array<int>").alias("ids")).mapInArrow(shipped("panelspark.llm.pieces", "decoded", model_path), "doc_id long, text string")
