"""N-gram Jaccard join: all pairs of documents whose word shingles overlap by a share, as components.

1. Every text becomes its set of distinct shingles (64-bit hashes); equal sets form one class.
2. Columns of one class overlap with nothing. A class of n shingles links only if at most n - ceil(t n) of them are its own
   alone, so classes with more are discarded at once. The test counts a fixed share of the columns only (those of some
   hash values); what it finds among these is a lower bound of the whole, so no link is lost.
3. The rest meet by prefixes: in one common order, rare columns first, two sets that may link share a column among the
   first n - ceil(t n) + 1 of each. Classes of a prefix column are chained in order of their sizes, and the chain is cut
   where the size bound rules a link out. Columns are counted per part of the classes before they are shuffled, and each
   part sends one row a column, so a frequent column is no hot key.
4. The components of these chains are the blocks of the product of documents by shingles with its transpose: overlap
   counts accumulate, column by column; pairs below the size-derived bounds are discarded. Large blocks are cut into
   sub-blocks of bounded bytes: first each by itself, then the members outside the largest component found so far
   against the whole block.
5. The links (a spanning forest from each sub-block) give the components by star rounds.

Null texts, empty texts and texts without words have the empty set, which links with nothing. A text with
fewer words than a shingle is one shingle, of all its words. Repeated rows are of one class. A row with a null doc_id
links like any other, and names no component unless it is alone. Ties cannot arise: the component is named by its
smallest doc_id. Columns of docs other than doc_id and text are never read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import U, byte_view, discard, grouped, lowered, mix, range_hashes, settled, shipped, slices, word_ranges
from .components import Forest, components

def doc_sets(column, width: int):
    """Row by row: (row, sorted distinct shingle hashes)."""
    data, off = byte_view(column)
    for i, j in slices(off):
        part, rows = lowered(data[off[i] : off[j]]), off[i : j + 1] - off[i]
        starts, ends, row = word_ranges(part, rows)
        h = range_hashes(part, starts, ends)
        first = np.searchsorted(row, np.arange(j - i + 1))
        gram = np.zeros(len(h), np.uint64)
        for k in range(width):
            m = max(0, len(h) - k)
            gram[:m] = mix(gram[:m] * U(3) + h[k : k + m] + U(k))
        for r in range(j - i):
            a, b = first[r], first[r + 1]
            if b - a >= width:
                yield i + r, np.unique(gram[a : b - width + 1])
            elif b > a:
                x = U(b - a)
                for k in range(a, b):
                    x = mix(np.array([x]) * U(7) + h[k : k + 1])[0]
                yield i + r, np.array([x], np.uint64)
            else:
                yield i + r, h[:0]


def digest(s: np.ndarray) -> int:
    return int.from_bytes(hashlib.blake2b(s.tobytes(), digest_size=8).digest(), "little", signed=True) or 1


def described(batches, width: int):
    """Rows (doc_id, text, text_hash) to (doc_id, text_hash, n_shingles, class)."""
    for batch in batches:
        n, d = np.zeros(batch.num_rows, np.int64), np.zeros(batch.num_rows, np.int64)
        for r, s in doc_sets(batch.column(1), width):
            n[r], d[r] = len(s), digest(s)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(n), pa.array(d)], ["doc_id", "text_hash", "n_shingles", "class"])


def _planes(x: np.ndarray, n: int) -> bytes:
    """The n low bytes of each number, byte by byte place: high places are nearly constant and compress away."""
    return np.ascontiguousarray(x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :n].T).tobytes()


def _from_planes(raw: bytes, m: int, n: int, at: int) -> np.ndarray:
    out = np.zeros((m, 8), np.uint8)
    out[:, :n] = np.frombuffer(raw, np.uint8, m * n, at).reshape(n, m).T
    return out.view("<u8").ravel()


def pack(ordered: np.ndarray, *others: np.ndarray) -> bytes:
    """Arrays of one length; the first ascends and is kept as differences."""
    raw = np.array([len(ordered), len(others)], np.int64).tobytes() + _planes(np.diff(ordered.astype(np.uint64), prepend=U(0)), 8)
    return zstandard.ZstdCompressor(level=1).compress(raw + b"".join(_planes(x.astype(np.int64), 8) for x in others))


def unpack(blob: bytes) -> list[np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(blob)
    m, n = map(int, np.frombuffer(raw, np.int64, 2))
    return [np.cumsum(_from_planes(raw, m, 8, 16), dtype=np.uint64)] + [_from_planes(raw, m, 8, 16 + 8 * m * (k + 1)).view(np.int64) for k in range(n)]


def _runs(x: np.ndarray) -> np.ndarray:
    """The starts of the runs of equal values, and the length."""
    return np.concatenate([[0], np.flatnonzero(x[1:] != x[:-1]) + 1, [len(x)]]) if len(x) else np.zeros(1, np.int64)


SHARED = 0  # in place of a class: several classes of one batch have the column


def columns_of(batches, width: int, share: int, buckets: int, most: int = 1 << 20):
    """Distinct columns of some megabytes of texts, those of share / 256 of the hash values: rows (bucket, blob) of columns
    and the one class each belongs to, or SHARED."""
    seen: set[int] = set()
    keys: list[np.ndarray] = []
    classes: list[int] = []
    held = 0

    def flush():
        k, c = np.concatenate(keys), np.repeat(np.array(classes, np.int64), list(map(len, keys)))
        # the bucket and 40 bits: columns that collide look shared, which discards nothing
        k = (((k >> U(40)) % U(buckets)) << U(40)) | (k & U((1 << 40) - 1))
        order = np.argsort(k, kind="stable")
        k, c = k[order], c[order]
        at = _runs(k)
        c = np.where(np.diff(at) > 1, SHARED, c[at[:-1]])
        k = k[at[:-1]]
        b = k >> U(40)
        cuts = _runs(b)
        blobs = []
        for x, y in zip(cuts[:-1], cuts[1:], strict=True):
            names, place = np.unique(c[x:y], return_inverse=True)
            blobs.append(pack(k[x:y] & U((1 << 40) - 1), place) + names.tobytes() + np.int64(len(names)).tobytes())
        return pa.RecordBatch.from_arrays([pa.array(b[cuts[:-1]].astype(np.int64)), pa.array(blobs, pa.binary())], ["bucket", "blob"])

    for batch in batches:
        for _, s in doc_sets(batch.column(0), width):
            d = digest(s)
            s = s[(s & U(255)) < U(share)]
            if not len(s) or d in seen:
                continue
            if len(seen) < 200_000:
                seen.add(d)
            keys.append(s)
            classes.append(d)
            held += len(s)
            if held > most:
                yield flush()
                keys, classes, held = [], [], 0
    if held:
        yield flush()


def own_columns(table: pa.Table, parts: int) -> pa.Table:
    """Of one bucket: rows (part, blob) of classes and how many columns each has alone."""
    k, c = [], []
    for blob in table.column("blob").to_pylist():
        n = int(np.frombuffer(blob[-8:], np.int64)[0])
        names = np.frombuffer(blob[-8 - 8 * n : -8], np.int64)
        x, place = unpack(blob[: -8 - 8 * n])
        k.append(x)
        c.append(names[place])
    k, c = np.concatenate(k), np.concatenate(c)
    order = np.argsort(k, kind="stable")
    k, c = k[order], c[order]
    at = _runs(k)
    low, high = np.minimum.reduceat(c, at[:-1]), np.maximum.reduceat(c, at[:-1])
    alone = low[(low == high) & (low != SHARED)]
    return _by_part(*np.unique(alone, return_counts=True), parts)


def _by_part(names: np.ndarray, numbers: np.ndarray, parts: int) -> pa.Table:
    part = names.view(np.uint64) % U(parts)
    order = np.lexsort((names.view(np.uint64), part))
    names, numbers, part = names[order], numbers[order], part[order]
    cuts = _runs(part)
    blobs = [pack(names[x:y].view(np.uint64), numbers[x:y]) for x, y in zip(cuts[:-1], cuts[1:], strict=True)]
    return pa.table({"part": pa.array(part[cuts[:-1]].astype(np.int64)), "blob": pa.array(blobs, pa.binary())})


def own_totals(table: pa.Table) -> pa.Table:
    both = [unpack(blob) for blob in table.column("blob").to_pylist()]
    names, numbers = np.concatenate([x[0] for x in both]), np.concatenate([x[1] for x in both])
    names, place = np.unique(names, return_inverse=True)
    return pa.table({"class": pa.array(names.view(np.int64)), "alone": pa.array(np.bincount(place, numbers, len(names)).astype(np.int64))})


def wanted_sets(batches, width: int, parts: int):
    """Rows (text, class) to (class, part, items): the sets of the texts that are of that class."""
    seen: set[int] = set()
    for batch in batches:
        cls, out = batch.column(1).to_pylist(), []
        for r, s in doc_sets(batch.column(0), width):
            if digest(s) == cls[r] and cls[r] not in seen:
                out.append((cls[r], cls[r] % parts, s.tobytes()))
                if len(seen) < 200_000:
                    seen.add(cls[r])
        columns = list(zip(*out, strict=True)) if out else [[]] * 3
        yield pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.binary())], ["class", "part", "items"])


def _members(table: pa.Table) -> tuple[list[int], list[np.ndarray]]:
    """Classes and sets of one part, each class once, in order."""
    sets = {c: np.frombuffer(x, np.uint64) for c, x in zip(table.column("class").to_pylist(), table.column("items").to_pylist(), strict=True)}
    return sorted(sets), [sets[c] for c in sorted(sets)]


def _bucket(keys: np.ndarray, buckets: int) -> np.ndarray:
    """Buckets ascend with the keys."""
    return ((keys >> U(32)) * U(buckets) >> U(32)).astype(np.int64)


def part_columns(table: pa.Table, buckets: int) -> pa.Table:
    """Of one part: rows (bucket, part, blob) of its columns and the number of its classes that have them."""
    keys, count = np.unique(np.concatenate(_members(table)[1]), return_counts=True)
    b = _bucket(keys, buckets)
    cuts = _runs(b)
    blobs = [pack(keys[x:y], count[x:y]) for x, y in zip(cuts[:-1], cuts[1:], strict=True)]
    part = table.column("part")[0].as_py()
    return pa.table({"bucket": pa.array(b[cuts[:-1]]), "part": pa.array([part] * len(blobs), pa.int64()), "blob": pa.array(blobs, pa.binary())})


def column_totals(table: pa.Table) -> pa.Table:
    """Of one bucket: for each part, one byte a column, ascending with the number of classes that have it (0: one class)."""
    both = [unpack(blob) for blob in table.column("blob").to_pylist()]
    keys, place = np.unique(np.concatenate([x[0] for x in both]), return_inverse=True)
    half, power = np.frexp(np.bincount(place, np.concatenate([x[1] for x in both]), len(keys)))
    code = np.minimum(8 * (power - 1) + ((half - 0.5) * 16).astype(np.int64), 255).astype(np.uint8)[place]
    ends = np.cumsum([0] + [len(x[0]) for x in both])
    blobs = [zstandard.ZstdCompressor(level=1).compress(code[x:y].tobytes()) for x, y in zip(ends[:-1], ends[1:], strict=True)]
    return pa.table({"bucket": table.column("bucket"), "part": table.column("part"), "codes": pa.array(blobs, pa.binary())})


FOUND = "class long, n long, items binary, bucket long, blob binary, u long, v long"


def _found(**columns) -> pa.Table:
    kinds = {"class": pa.int64(), "n": pa.int64(), "items": pa.binary(), "bucket": pa.int64(), "blob": pa.binary(), "u": pa.int64(), "v": pa.int64()}
    size = len(next(iter(columns.values())))
    return pa.table({k: pa.array(columns[k], t) if k in columns else pa.nulls(size, t) for k, t in kinds.items()})


def prefixes(table: pa.Table, totals: pa.Table, top: int, bottom: int, buckets: int) -> pa.Table:
    """Of one part, three kinds of rows: (class, n, items) with the columns it shares with others, for classes with shared
    columns in their prefix; (bucket, blob) of prefix columns, runs of sizes and a class of each run; links (u, v) of runs."""
    from .components import Forest

    if not table.num_rows:
        return _found(u=[])
    classes, sets = _members(table)
    keys = np.unique(np.concatenate(sets))
    answers = sorted(zip(totals.column("bucket").to_pylist(), totals.column("codes").to_pylist(), strict=True))
    code = np.frombuffer(b"".join(zstandard.ZstdDecompressor().decompress(x) for _, x in answers), np.uint8)
    kept, near, place = [], [], []
    for c, s in zip(classes, sets, strict=True):
        rank = code[np.searchsorted(keys, s)]
        shared = np.flatnonzero(rank)
        length = len(s) - (-(-len(s) * top // bottom)) + 1 - (len(s) - len(shared))
        if length > 0:
            first = shared[np.lexsort((s[shared], rank[shared]))[:length]]
            near.append(s[first])
            place.append(np.full(len(first), len(kept)))
            kept.append((c, len(s), s[shared].tobytes()))
    if not kept:
        return _found(u=[])
    names, sizes = np.array([x[0] for x in kept], np.int64), np.array([x[1] for x in kept], np.int64)
    k, c = np.concatenate(near), np.concatenate(place)
    order = np.lexsort((sizes[c], k))
    k, c = k[order], c[order]
    n = sizes[c]
    joined = (k[1:] == k[:-1]) & (n[:-1] * bottom >= n[1:] * top)
    forest = Forest()
    for a, b in set(zip(names[c[:-1][joined]].tolist(), names[c[1:][joined]].tolist(), strict=True)):
        forest.join(a, b)
    u, v = forest.links()
    starts = np.concatenate([[0], np.flatnonzero(~joined) + 1])
    ends = np.concatenate([starts[1:], [len(k)]]) - 1
    k, c, low, high = k[starts], names[c[starts]], n[starts], n[ends]
    b = _bucket(k, buckets)
    cuts = _runs(b)
    blobs = [pack(k[x:y], c[x:y], low[x:y], high[x:y]) for x, y in zip(cuts[:-1], cuts[1:], strict=True)]
    return pa.concat_tables([_found(**{"class": names, "n": sizes, "items": [x[2] for x in kept]}), _found(bucket=b[cuts[:-1]], blob=blobs), _found(u=u, v=v)])


def chained(table: pa.Table, top: int, bottom: int) -> pa.Table:
    """Links (u, v) of the runs of one bucket that share a column and whose sizes may link."""
    from .components import Forest

    k, c, low, high = (np.concatenate(x) for x in zip(*(unpack(blob) for blob in table.column("blob").to_pylist()), strict=True))
    order = np.lexsort((low, k))
    k, c, low, high = k[order], c[order], low[order], high[order]
    column = np.concatenate([[0], np.cumsum(k[1:] != k[:-1])])
    reach = np.maximum.accumulate((column << 40) + high) - (column << 40)  # the largest size so far, column by column
    joined = (k[1:] == k[:-1]) & (reach[:-1] * bottom >= low[1:] * top)
    forest = Forest()
    for a, b in set(zip(c[:-1][joined].tolist(), c[1:][joined].tolist(), strict=True)):
        forest.join(a, b)
    u, v = forest.links()
    return pa.table({"u": pa.array(u, pa.int64()), "v": pa.array(v, pa.int64())})


def overlaps(sets: list[np.ndarray], dense: int = 16, most: int = 1 << 22) -> np.ndarray:
    """The product of the incidence matrix of sets with its transpose, without columns of one set. Columns of at least one in
    `dense` of the sets are multiplied as dense strips, the others entry by entry."""
    m = len(sets)
    rows = np.repeat(np.arange(m), [len(s) for s in sets])
    _, column, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    out = np.zeros((m, m), np.int64)
    full = count * dense >= max(m, 32)
    number = np.cumsum(full) - 1
    keep = full[column]
    r, c = rows[keep], number[column[keep]]
    order = np.argsort(c, kind="stable")
    r, c = r[order], c[order]
    strips = np.zeros((m, m), np.float32)  # whole numbers far below 2**24
    for lo in range(0, int(full.sum()), 2048):
        a, b = np.searchsorted(c, [lo, lo + 2048])
        strip = np.zeros((m, 2048), np.float32)
        strip[r[a:b], c[a:b] - lo] = 1.0
        strips += strip @ strip.T
    out += strips.astype(np.int64)
    keep = (count[column] > 1) & ~full[column]
    r, c = rows[keep], column[keep]
    order = np.lexsort((r, c))
    r, c = r[order], c[order]
    at = _runs(c)
    later = np.repeat(at[1:], np.diff(at)) - np.arange(len(r)) - 1  # entries of the column below this one
    total = np.concatenate([[0], np.cumsum(later)])
    lo = 0
    flat = np.zeros(m * m, np.int64)
    while lo < len(r):
        hi = max(lo + 1, int(np.searchsorted(total, total[lo] + most, side="right")) - 1)
        e = np.repeat(np.arange(lo, hi), later[lo:hi])
        other = e + 1 + np.arange(len(e)) - np.repeat(total[lo:hi] - total[lo], later[lo:hi])
        flat += np.bincount(r[e] * m + r[other], minlength=m * m)
        lo = hi
    upper = flat.reshape(m, m)
    return out + upper + upper.T


def product_links(classes: list[int], sets: list[np.ndarray], size: np.ndarray, side: np.ndarray, top: int, bottom: int):
    """Links of one block. side: 1 or 2 for its rows and columns, 0 where it is one sub-block; pairs within one side are left
    to others. sets may leave out columns of one class, size counts them."""
    from .components import Forest

    both = overlaps(sets)
    small, large = np.minimum(size[:, None], size[None]), np.maximum(size[:, None], size[None])
    linked = (small * bottom >= large * top) & (both * (top + bottom) >= (size[:, None] + size[None]) * top)
    linked &= (side[:, None] != side[None]) | (side[:, None] == 0)
    forest = Forest()
    for a, b in zip(*np.nonzero(np.triu(linked, 1)), strict=True):
        forest.join(classes[a], classes[b])
    return forest


def block_links(batches, top: int, bottom: int):
    """Sorted rows (block, i, j, side, class, n, items): the links of each sub-block."""
    key, held = None, {}

    def done():
        (side, classes), (n, sets) = zip(*held, strict=True), zip(*held.values(), strict=True)
        u, v = product_links(list(classes), list(sets), np.array(n), np.array(side), top, bottom).links() if len(held) > 1 else (np.zeros(0, np.int64),) * 2
        return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])

    for batch in batches:
        for *k, side, c, n, items in zip(*(batch.column(x).to_pylist() for x in range(7)), strict=True):
            if k != key and held:
                yield done()
                held = {}
            key = k
            held[side, c] = (n, np.frombuffer(items, np.uint64))
    if held:
        yield done()


HERE = "panelspark.llm.jaccard"
BROADCAST_ROWS = 1 << 18


def _small(df: DataFrame, count: int) -> DataFrame:
    """df, marked for broadcast if it has few rows."""
    return F.broadcast(df) if count <= BROADCAST_ROWS else df


def _products(placed: DataFrame, top: int, bottom: int) -> DataFrame:
    keyed = placed.select("block", "i", "j", "side", "class", "n", "items")
    return keyed.repartition("block", "i", "j").sortWithinPartitions("block", "i", "j").mapInArrow(shipped(HERE, "block_links", top, bottom), "u long, v long")


def _across(members: DataFrame, sets: DataFrame, links: DataFrame, block_rows: int, block_bytes: int, top: int, bottom: int) -> DataFrame:
    """Links between the sub-blocks of the large blocks: the members outside a block's largest component against the block.

    members: (class, block, n, subs) of the large blocks, links: what their sub-blocks gave."""
    named = members.join(components(links).withColumnRenamed("node", "class"), "class", "left").withColumn("root", F.coalesce("root", "class"))
    sizes = named.groupBy("block", "root").agg(F.count("*").alias("m"))
    most = sizes.groupBy("block").agg(F.max_by("root", F.struct("m", "root")).alias("main"))
    named = settled(named.join(most, "block"))
    rest = named.where("root <> main").groupBy("block").agg(F.greatest(F.ceil(F.count("*") / F.lit(block_rows)), F.ceil(F.sum("n") * 8 / F.lit(block_bytes))).cast("int").alias("rows"))
    deal = lambda k: F.pmod(F.xxhash64("class"), F.col(k)).cast("int")
    dealt = sets.join(named.join(rest, "block").select("class", "block", "root", "main", "subs", "rows"), "class")
    as_rows = dealt.where("root <> main").select("block", deal("rows").alias("i"), F.explode(F.sequence(F.lit(0), F.col("subs") - 1)).alias("j"), F.lit(1).alias("side"), "class", "n", "items")
    as_columns = dealt.select("block", F.explode(F.sequence(F.lit(0), F.col("rows") - 1)).alias("i"), deal("subs").alias("j"), F.lit(2).alias("side"), "class", "n", "items")
    return _products(as_rows.unionByName(as_columns), top, bottom)


def similar(docs: DataFrame, width: int = 3, top: int = 90, bottom: int = 100, block_bytes: int = 4 << 20, block_rows: int = 512, bucket_bytes: int = 8 << 20) -> DataFrame:
    """doc_id, n_shingles and component_id of each row of docs(doc_id, text); links need a Jaccard value of top / bottom."""
    plain = docs.select("doc_id", "text").withColumn("text_hash", F.xxhash64("text"))
    rows = settled(plain.mapInArrow(shipped(HERE, "described", width), "doc_id long, text_hash long, n_shingles long, class long"))
    classes = settled(rows.where("n_shingles > 0").groupBy("class").agg(F.min("doc_id").alias("rep"), F.min(F.struct("text_hash", "doc_id")).alias("at"), F.first("n_shingles").alias("n"), F.count("*").alias("copies")))
    total = classes.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    # classes with too many columns of their own link with nothing
    share = min(256, 640 * (bottom - top) // bottom + 1)
    buckets = total * share // 256 * 6 // bucket_bytes + 8
    columns = plain.select("text").mapInArrow(shipped(HERE, "columns_of", width, share, buckets), "bucket long, blob binary")
    alone = columns.groupBy("bucket").applyInArrow(grouped(HERE, "own_columns", buckets), "part long, blob binary").groupBy("part").applyInArrow(grouped(HERE, "own_totals"), "class long, alone long")
    left = classes.join(alone, "class", "left").where(F.coalesce("alone", F.lit(0)) <= F.col("n") - F.ceil(F.col("n") * top / F.lit(bottom)))
    left = settled(left.select("class", "n", "at.text_hash", F.col("at.doc_id").alias("doc_id")))
    few, size = left.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
    parts = size * 8 // bucket_bytes + 8
    wanted = plain.alias("d").join(_small(left, few).alias("w"), (F.col("d.text_hash") == F.col("w.text_hash")) & F.col("d.doc_id").eqNullSafe(F.col("w.doc_id")))
    sets = settled(wanted.select("d.text", "w.class").mapInArrow(shipped(HERE, "wanted_sets", width, parts), "class long, part long, items binary"))
    counted = sets.groupBy("part").applyInArrow(grouped(HERE, "part_columns", parts), "bucket long, part long, blob binary")
    totals = counted.groupBy("bucket").applyInArrow(grouped(HERE, "column_totals"), "bucket long, part long, codes binary")
    found = settled(sets.groupBy("part").cogroup(totals.groupBy("part")).applyInArrow(grouped(HERE, "prefixes", top, bottom, parts), FOUND))
    discard(sets, left)
    chains = found.where("blob is not null").select("bucket", "blob").groupBy("bucket").applyInArrow(grouped(HERE, "chained", top, bottom), "u long, v long")
    blocks = components(found.where("u is not null").select("u", "v").union(chains))
    kept = found.where("items is not null").select("class", "n", "items")
    members = kept.select("class", "n").join(blocks.select(F.col("node").alias("class"), F.col("root").alias("block")), "class")
    subs = members.groupBy("block").agg(F.greatest(F.ceil(F.count("*") / F.lit(block_rows)), F.ceil(F.sum("n") * 8 / F.lit(block_bytes))).cast("int").alias("subs"))
    members = settled(members.join(subs, "block").select("class", "block", "n", "subs"))
    sub = F.pmod(F.xxhash64("class"), F.col("subs")).cast("int")
    placed = kept.join(members.select("class", "block", sub.alias("i"), sub.alias("j"), F.lit(0).alias("side")), "class")
    links = settled(_products(placed, top, bottom))
    large = members.where("subs > 1")
    if not large.isEmpty():
        inside = links.join(large.select(F.col("class").alias("u")), "u", "left_semi").select("u", "v")
        links = links.union(settled(_across(large, kept, inside, block_rows, block_bytes, top, bottom)))
    joined = components(links).withColumnRenamed("node", "class")
    # the smallest doc_id of each component, by class
    named = classes.select("class", "rep").join(joined, "class")
    least = named.groupBy("root").agg(F.min("rep").alias("least"))
    linked = named.join(least, "root").select("class", "least")
    of_class = settled(classes.join(linked, "class", "left").select("class", "copies", F.coalesce("least", "rep").alias("component_id")))
    discard(found, members, classes)
    # classes of a thousandth of all rows or more are a thousand at most
    hot = F.broadcast(of_class.where(F.col("copies") * 1000 >= max(rows.count(), 1000)))
    plain = rows.withColumn("class", F.when(F.col("n_shingles") > 0, F.col("class")))
    cold = plain.join(hot.select("class"), "class", "left_anti").join(of_class.select("class", "component_id"), "class", "left")
    out = cold.select("doc_id", "n_shingles", "component_id").union(plain.join(hot, "class").select("doc_id", "n_shingles", "component_id"))
    return out.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def representatives(docs: DataFrame, width: int = 5, top: int = 80, bottom: int = 100) -> DataFrame:
    """docs without those that are linked with a smaller doc_id: one of each component stays (repeated ids: one row).

    Rows with a null doc_id name no document and stay. The ids that go, and those of several rows that stay, are counted; while
    they are few they are broadcast and no text is shuffled.
    """
    stays = F.col("doc_id") == F.col("component_id")
    ids = settled(similar(docs, width, top, bottom).where(F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.sum(stays.cast("int")).alias("n")).where("n <> 1"))
    gone, several = ids.where("n = 0").count(), ids.where("n > 1").count()
    kept = docs.join(_small(ids.select("doc_id"), gone + several), "doc_id", "left_anti").select(*docs.columns)
    if several:
        repeated = docs.join(_small(ids.where("n > 1").select("doc_id"), several), "doc_id", "left_semi").select(*docs.columns)
        kept = kept.unionByName(repeated.dropDuplicates(["doc_id"]))
    return kept
