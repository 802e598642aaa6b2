"""Helpers shared by the operators: shared scratch tables, byte-level views of Arrow text columns, word hashing."""

from __future__ import annotations

import hashlib
import sys
import types

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from halograph.graph.scratch import Scratch  # noqa: F401  the operators take it from here

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z only. All-ASCII texts take the quick built-in; others go letter by letter."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, _UPPER, _LOWER))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def worker_store(name: str) -> dict:
    """A dictionary that lives as long as the Python worker, for tables built once in each worker."""
    box = sys.modules.setdefault("_halograph_worker_store", types.ModuleType("_halograph_worker_store"))
    return box.__dict__.setdefault(name, {})


def text_bytes(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(all bytes, offsets) of a string column without copying; a null has no bytes."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.large_string())
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, off, data = column.buffers()
    offsets = np.frombuffer(off, np.int64, len(column) + 1, column.offset * 8)
    whole = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return whole[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(batch: pa.RecordBatch, text: str, most_bytes: int, line_bytes: int = 0):
    """Cuts a batch so that each part holds at most so many bytes of text, or a single row; a line end counts as
    ``line_bytes`` more where work is done by lines."""
    col = batch.column(batch.schema.get_field_index(text))
    data, off = text_bytes(col)
    if line_bytes:
        off = off + line_bytes * np.searchsorted(np.flatnonzero(data == 10), off)
    start = 0
    while start < batch.num_rows:
        end = int(np.searchsorted(off, off[start] + most_bytes, "right")) - 1
        end = min(max(end, start + 1), batch.num_rows)
        yield batch.slice(start, end - start)
        start = end


def _powers() -> tuple[int, int]:
    base = 0x9E3779B97F4A7C15 | 1
    return base, pow(base, -1, 1 << 64)


def power_table(n: int, inverse: bool = False) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64, kept in the worker and grown as needed."""
    store = worker_store("powers")
    got = store.get(inverse)
    if got is None or len(got) < n:
        base = _powers()[inverse]
        size = max(1 << 16, 1 << int(n - 1).bit_length()) if n > 1 else 1 << 16
        got = np.full(size, base, np.uint64)
        got[0] = 1
        np.multiply.accumulate(got, out=got)
        store[inverse] = got
    return got[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, long: int = 0) -> np.ndarray:
    """64-bit hashes of data[start:end] by a polynomial over the whole buffer; spans over ``long`` by a keyed digest."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    terms = (data.astype(np.uint64) + np.uint64(1)) * power_table(len(data))
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(terms, out=total[1:])
    got = (total[ends] - total[starts]) * power_table(len(data) + 1, True)[starts]
    got = mix(got ^ (ends - starts).astype(np.uint64))
    if long:  # a polynomial modulo a power of two is weak on long regular strings
        for k in np.flatnonzero(ends - starts > long).tolist():
            got[k] = int.from_bytes(hashlib.blake2b(data[starts[k] : ends[k]].tobytes(), digest_size=8).digest(), "little")
    return got


def runs(mask: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, row) of the maximal runs of true bytes; no run crosses a row's bounds."""
    n = len(mask)
    edge = np.zeros(n + 1, bool)
    edge[1:n] = mask[1:] != mask[:-1]
    edge[0] = edge[n] = True
    edge[offsets] = True
    cut = np.flatnonzero(edge)
    keep = mask[cut[:-1]] if n else np.zeros(0, bool)
    starts, ends = cut[:-1][keep], cut[1:][keep]
    return starts, ends, np.searchsorted(offsets, starts, "right") - 1


WORD_BREAK = np.ones(256, bool)
WORD_BREAK[[0x20, *range(0x09, 0x0E)]] = False
LOWER_BYTES = np.arange(256, dtype=np.uint8)
LOWER_BYTES[65:91] += 32
