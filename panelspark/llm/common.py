"""What the document operators share: shipping functions to workers, Arrow text access, scratch space."""

from __future__ import annotations

import importlib
import os
import tempfile
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def shipped(module: str, function: str, *args):
    """A function of an iterator of record batches that workers can load without a prepared search path.

    It is a closure, so it travels by value; the worker imports the named function when a task starts.
    """
    root = ROOT

    def run(batches):
        import importlib
        import sys

        if root not in sys.path:
            sys.path.insert(0, root)
        yield from getattr(importlib.import_module(module), function)(batches, *args)
        importlib.import_module("panelspark.llm.common").give_back()

    return run


def give_back() -> None:
    """Workers are used again: what a task has freed goes back to the system, where the C library can do that."""
    import ctypes

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:
        pass


def grouped(module: str, function: str, *args):
    """The same for functions of one Arrow table, or of two for cogroups; the number of parameters tells Spark no keys are wanted."""
    root = ROOT

    def called(*tables):
        import importlib
        import sys

        if root not in sys.path:
            sys.path.insert(0, root)
        made = getattr(importlib.import_module(module), function)(*tables, *args)
        importlib.import_module("panelspark.llm.common").give_back()
        return made

    def one(table):
        return called(table)

    def two(left, right):
        return called(left, right)

    import inspect

    wanted = len(inspect.signature(getattr(importlib.import_module(module), function)).parameters) - len(args)
    return two if wanted == 2 else one


def table(spark, sf_dir: str, name: str):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark) -> str:
    """A fresh folder that all executors share: below spark.checkpoint.dir, or a temporary one where that is unset."""
    base = spark.conf.get("spark.checkpoint.dir", None) or os.environ.get("PANELSPARK_SCRATCH")
    if not base:
        if not spark.conf.get("spark.master", "local").split("[")[0] == "local":
            raise RuntimeError("on a cluster, spark.checkpoint.dir must name a folder that all executors share")
        base = tempfile.gettempdir() + "/panelspark-scratch"
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def settled(df):
    """The rows of df, written to the shared scratch folder and read again: cuts the lineage, survives lost executors."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.settled_at = path
    return out


def discard(*steps):
    """Deletes the files of settled frames that no later step reads."""
    for step in steps:
        jvm, path = step.sparkSession._jvm, step.settled_at
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(step.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(where, True)


def texts(column) -> list[str]:
    return ["" if t is None else t for t in column.to_pylist()]


def byte_view(column) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string column and its n + 1 offsets; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    n = len(column)
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, dtype=kind)[column.offset : column.offset + n + 1].astype(np.int64) if n else np.zeros(1, np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def slices(offsets: np.ndarray, most: int = 1 << 19):
    """Ranges of rows that hold at most so many bytes (a longer row stands alone), so that temporaries stay small."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, side="right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


U = np.uint64
_BASE = U(0x9E3779B97F4A7C15 | 1)
_POWERS = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _powers(n: int):
    """Powers of an odd base and of its inverse modulo 2**64."""
    if len(_POWERS[0]) < n:
        inverse = U(pow(int(_BASE), -1, 1 << 64))
        size = max(n, 1 << 16)
        for k, b in ((0, _BASE), (1, inverse)):
            x = np.full(size, b, np.uint64)
            x[0] = U(1)
            _POWERS[k] = np.multiply.accumulate(x)
    return _POWERS


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit words (xor-shift and multiply rounds)."""
    x = x ^ (x >> U(32))
    x = x * U(0xD6E8FEB86659FD93)
    x = x ^ (x >> U(32))
    x = x * U(0xD6E8FEB86659FD93)
    return x ^ (x >> U(32))


def range_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, most: int = 1 << 19) -> np.ndarray:
    """64-bit content hashes of many byte ranges of one buffer, by prefix sums. The ranges ascend; they are taken in pieces
    that span `most` bytes (or one longer range), so that a long text needs no more than a short one."""
    out = np.empty(len(starts), np.uint64)
    i = 0
    while i < len(starts):
        base = int(starts[i])
        j = max(i + 1, int(np.searchsorted(ends[i:], base + most, side="right")) + i)
        lo, hi = starts[i:j] - base, ends[i:j] - base
        n = int(hi.max())
        up, down = _powers(n + 1)
        total = np.zeros(n + 1, np.uint64)
        np.cumsum((data[base : base + n].astype(np.uint64) + U(1)) * up[:n], out=total[1:])
        out[i:j] = mix((total[hi] - total[lo]) * down[lo] + (hi - lo).astype(np.uint64))
        i = j
    return out


def lowered(data: np.ndarray) -> np.ndarray:
    """A-Z to a-z, other bytes unchanged."""
    return np.where((data >= 65) & (data <= 90), data | 32, data).astype(np.uint8)


def word_ranges(data: np.ndarray, offsets: np.ndarray):
    """Start, end and row of each run of bytes other than space and \\t..\\r; runs never cross rows."""
    if not len(data):
        z = np.zeros(0, np.int64)
        return z, z, z
    inside = ~((data == 32) | ((data >= 9) & (data <= 13)))
    first = np.zeros(len(data) + 1, bool)
    first[offsets] = True
    before = np.zeros(len(data), bool)
    before[1:] = inside[:-1]
    starts = np.flatnonzero(inside & (~before | first[:-1]))
    after = np.zeros(len(data), bool)
    after[:-1] = inside[1:]
    ends = np.flatnonzero(inside & (~after | first[1:])) + 1
    return starts, ends, np.searchsorted(offsets, starts, side="right") - 1
