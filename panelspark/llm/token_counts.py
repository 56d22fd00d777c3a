"""Token counts of whole texts by a public subword model, with overlap resynchronisation for huge ones.

The counts equal those of the library on the whole text. Texts up to `chunk` characters are cut at the
boundaries that no merge can cross; each distinct unit is encoded once by the library and cached. Longer texts
are encoded as overlapping chunks with offsets: two neighbouring encodings are spliced at the first boundary
inside their overlap that both have and that is proven stable, and the overlap is doubled where there is none.

Why a boundary is proven: a byte-pair model only joins adjacent pieces into a piece of its vocabulary. If no piece
holds a word mark after another character, then no merge, at any stage, crosses a place before a mark that
follows another character. The same holds on both sides of a character that no longer piece contains.

Null and empty texts have 0 tokens. Repeated rows give repeated results. Other columns are ignored.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import shipped, texts

MARK = "▁"
SCHEMA = "doc_id long, n_bytes long, n_tokens long, over_limit boolean, n_chunks long"
CACHE = 200_000


class UnitCounter:
    """Counts and offsets of tokens by way of units between stable boundaries."""

    def __init__(self, path: str):
        import sentencepiece
        from sentencepiece import sentencepiece_model_pb2 as pb

        model = pb.ModelProto()
        with open(path, "rb") as f:
            model.ParseFromString(f.read())
        spec = model.normalizer_spec
        if spec.name != "identity" or spec.remove_extra_whitespaces or not spec.escape_whitespaces:
            raise ValueError("only models with the identity normaliser are supported")
        normal = [p.piece for p in model.pieces if p.type == 1]
        self.decomposes = not any(MARK in p.lstrip(MARK) for p in normal)
        self.prefix = MARK if spec.add_dummy_prefix else ""
        alone = "\n\t\r" if not any(c in p for p in normal for c in "\n\t\r") else ""
        # the units: runs of marks with what follows, and each run of characters that no piece contains
        self.unit = re.compile(f"[{alone}]+|{MARK}*[^{MARK}{alone}]+|{MARK}+" if alone else f"{MARK}*[^{MARK}]+|{MARK}+")
        spec.add_dummy_prefix = False
        self.library = sentencepiece.SentencePieceProcessor(model_proto=model.SerializeToString())
        self.cache: dict[str, int] = {}

    def units(self, text: str) -> list[str]:
        if not text:
            return []
        text = self.prefix + text.replace(" ", MARK)
        return self.unit.findall(text) if self.decomposes else [text]

    def learn(self, units) -> None:
        new = [u for u in set(units) if u not in self.cache]
        if len(self.cache) + len(new) > CACHE:
            self.cache.clear()
            new = list(set(units))
        self.cache.update(zip(new, map(len, self.library.encode(new, num_threads=1)), strict=True))

    def count(self, text: str) -> int:
        units = self.units(text)
        get = self.cache.get
        found = [get(u) for u in units]
        if None in found:
            self.learn(units)
            found = [self.cache[u] for u in units]
        return sum(found)

    def boundaries(self, text: str, at: int) -> dict[int, int]:
        """Of a chunk that begins at character `at` of a document: stable boundary -> tokens of the chunk before it.

        A chunk that begins inside a document begins at a space, so the mark of the prefix stands for no character.
        """
        units = self.unit.findall((self.prefix if at == 0 else "") + text.replace(" ", MARK))
        self.learn(units)
        place, total, out = at - (len(self.prefix) if at == 0 else 0), 0, {at: 0}
        for u in units:
            out[max(place, at)] = total
            place += len(u)
            total += self.cache[u]
        out[place] = total
        return out

    def count_long(self, text: str, chunk: int, overlap: int) -> tuple[int, int]:
        """Tokens of a long text and the number of chunks; memory is bounded by the chunk unless no boundary exists."""
        if not self.decomposes or len(text) <= chunk:
            return self.count(text), 1
        total, start, pieces = 0, 0, 0
        while True:
            stop, pieces = min(start + chunk, len(text)), pieces + 1
            if stop == len(text):
                left = self.boundaries(text[start:], start)
                return total + left[len(text)], pieces
            width = overlap
            while True:
                left = self.boundaries(text[start:stop], start)
                begin = max(start + 1, stop - width)
                right = self.boundaries(text[begin : min(begin + 2 * width, len(text))], begin)
                # a chunk's own ends are no boundaries of the text; what both sides have strictly inside is
                common = [b for b in right if begin < b < stop and b in left]
                if common:
                    splice = common[len(common) // 2]
                    break
                if width >= stop - start:  # none in the whole chunk: lengthen it
                    stop = min(stop + chunk, len(text))
                    if stop == len(text):
                        return total + self.boundaries(text[start:], start)[len(text)], pieces
                width *= 2
            total, start = total + left[splice], splice


_COUNTERS: dict[str, UnitCounter] = {}


def counted(batches, path: str, limit: int, chunk: int, overlap: int):
    counter = _COUNTERS.setdefault(path, None) or UnitCounter(path)
    _COUNTERS[path] = counter
    for batch in batches:
        ids, rows = batch.column(0), texts(batch.column(1))
        found = [counter.count_long(t, chunk, overlap) for t in rows]
        n = [a for a, _ in found]
        yield pa.RecordBatch.from_arrays(
            [ids, pa.array([len(t.encode()) for t in rows], pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_()), pa.array([b for _, b in found], pa.int64())],
            ["doc_id", "n_bytes", "n_tokens", "over_limit", "n_chunks"],
        )


def token_counts(docs: DataFrame, model_path: str, limit: int = 4096, chunk: int = 65_536, overlap: int = 512) -> DataFrame:
    """One row for each row of docs(doc_id, text). Narrow: no shuffle, whatever the size."""
    return docs.select("doc_id", "text").mapInArrow(shipped("panelspark.llm.token_counts", "counted", model_path, limit, chunk, overlap), SCHEMA)
