"""Burrows-Wheeler transform and common prefixes of a collection of short byte strings, built column by column.

Each round puts the next symbol (from the right) of every string in front of its suffix. The transform, the common
prefixes with the row before and the suffix names are read and rewritten from start to end by each round, in files once
a collection is large, so memory holds a block of rows and a few numbers for each string. Byte 255 marks the front of a string; UTF-8 has none.
"""

from __future__ import annotations

import os
import tempfile

import numpy as np

END = 255
#: Rows of a file that are held at once.
BLOCK_ROWS = 1 << 18
#: Rows (suffixes) up to which a collection stays in memory.
MEMORY_ROWS = 8 << 20
#: A suffix is named string * SHIFT + length; strings are shorter than SHIFT.
SHIFT = 128
_FILES = (("bwt", np.uint8), ("lcp", np.uint8), ("name", np.uint32))


class _Files:
    """One generation of the rows, as files that are only appended to and read through."""

    def __init__(self, folder: str, generation: int):
        self.paths = [os.path.join(folder, f"{what}-{generation % 2}") for what, _ in _FILES]
        self.n, self.out = 0, [open(p, "wb") for p in self.paths]

    def put(self, *columns: np.ndarray) -> None:
        for f, c, (_, kind) in zip(self.out, columns, _FILES):
            c.astype(kind, copy=False).tofile(f)
        self.n += len(columns[0])

    def close(self) -> None:
        for f in self.out:
            f.close()

    def blocks(self, size: int, *which: int):
        """Reads the columns asked for, so many rows at a time; ``size`` may be sent anew."""
        files = [open(self.paths[k], "rb") for k in which]
        try:
            while True:
                size = (yield [np.fromfile(f, _FILES[k][1], size) for f, k in zip(files, which)]) or size
        finally:
            for f in files:
                f.close()


class _Memory:
    """The same for collections that are small enough to stay in memory."""

    def __init__(self, folder: str, generation: int):
        self.n, self.parts = 0, [[] for _ in _FILES]

    def put(self, *columns: np.ndarray) -> None:
        for part, c, (_, kind) in zip(self.parts, columns, _FILES):
            part.append(c.astype(kind, copy=False))
        self.n += len(columns[0])

    def close(self) -> None:
        self.parts = [p[0] if len(p) == 1 else np.concatenate(p) for p in self.parts]

    def blocks(self, size: int, *which: int):
        at = 0
        while True:
            rows = [self.parts[k][at : at + size] for k in which]
            at += size
            size = (yield rows) or size


def _range_minima(values: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
    """Least of values[start:stop] for non-empty ranges; falling starts keep the passes between ranges empty."""
    if not len(start):
        return np.zeros(0, values.dtype)
    order = np.argsort(-start, kind="stable")
    pairs = np.stack([start[order], stop[order]], 1).ravel()
    got = np.empty(len(start), values.dtype)
    got[order] = np.minimum.reduceat(np.append(values, np.uint8(255)), pairs)[::2]
    return got


def build(data: np.ndarray, starts: np.ndarray, lengths: np.ndarray, folder: str | None = None, block: int = BLOCK_ROWS, in_memory: int = MEMORY_ROWS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bwt, lcp, names) of all suffixes of data[start:start+length], empty ones first; lcp[i] is with row i - 1.

    Collections of more than ``in_memory`` rows go through files in ``folder`` (the task's temporary folder).
    """
    if len(starts) + int(lengths.sum()) <= in_memory:
        rows = _construct(data, starts.astype(np.int64), lengths.astype(np.int64), _Memory, "", block)
        return tuple(next(rows.blocks(rows.n, 0, 1, 2)))
    with tempfile.TemporaryDirectory(dir=folder) as own:
        rows = _construct(data, starts.astype(np.int64), lengths.astype(np.int64), _Files, own, block)
        return tuple(next(rows.blocks(rows.n, 0, 1, 2)))


def _construct(data, starts, lengths, kind, folder, block):
    m = len(starts)
    rows = kind(folder, 0)
    symbol = lambda i, done: np.where(lengths[i] > done, data[np.minimum(starts[i] + np.maximum(lengths[i] - 1 - done, 0), max(len(data) - 1, 0))] if len(data) else END, END).astype(np.uint8)
    first = symbol(np.arange(m), 0)
    rows.put(first, np.zeros(m, np.uint8), np.arange(m, dtype=np.uint32) * SHIFT)
    rows.close()
    counts = np.bincount(first, minlength=256)
    fresh, owner = np.arange(m), np.arange(m)  # places of the rows of the last round, rising, and their strings
    for done in range(1, int(lengths.max(initial=0)) + 1):
        base = m + np.concatenate([[0], np.cumsum(counts[:END])[:-1]])
        dest, lcp, who = _places(rows, fresh, owner, base, block)
        new = who >= 0
        order = np.argsort(dest[new])
        fresh, owner, fresh_lcp = dest[new][order], who[new][order], lcp[new][order]
        mend = np.argsort(dest[~new])
        front = symbol(owner, done)
        rows = _merge(rows, kind(folder, done), fresh, front, fresh_lcp, owner * SHIFT + done, dest[~new][mend], lcp[~new][mend], block)
        counts += np.bincount(front, minlength=256)
    return rows


def _places(rows, fresh, owner, base, block) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where the extensions of the fresh rows go, with their common prefix, and the older rows whose prefix changes.

    Reads the transform once. The rows of a symbol c, in order, are the next generation's rows that begin with c.
    """
    take = rows.blocks(block, 0, 1)
    seen = np.zeros(256, np.int64)  # rows of each symbol so far
    least = np.full(256, 255, np.uint8)  # least common prefix since the last row of each symbol
    last_fresh = np.zeros(256, bool)
    out = []
    for a in range(0, rows.n, block):
        bwt, lcp = next(take)
        lo, hi = np.searchsorted(fresh, [a, a + len(bwt)])
        is_new = np.zeros(len(bwt), bool)
        is_new[fresh[lo:hi] - a] = True
        string = np.full(len(bwt), -1, np.int64)
        string[fresh[lo:hi] - a] = owner[lo:hi]
        order = np.argsort(bwt, kind="stable")
        size = np.bincount(bwt, minlength=256)
        heads = np.concatenate([[0], np.cumsum(size)[:-1]])
        sorted_bwt = bwt[order]
        leads = np.zeros(len(order), bool)
        leads[heads[size > 0]] = True
        new = is_new[order]
        before_new = np.empty(len(order), bool)
        before_new[1:] = new[:-1]
        before_new[leads] = last_fresh[sorted_bwt[leads]]
        need = np.flatnonzero((new | before_new) & (sorted_bwt != END))
        c = sorted_bwt[need]
        at = order[need]
        lead = leads[need]
        start = np.where(lead, 0, order[np.maximum(need - 1, 0)] + 1)
        value = _range_minima(lcp, start, at + 1)
        value = np.where(lead, np.minimum(value, least[c]), value).astype(np.int64) + 1
        value[lead & (seen[c] == 0)] = 0
        out.append((base[c] + seen[c] + need - heads[c], np.minimum(value, 254), np.where(new[need], string[at], -1)))
        present = np.flatnonzero(size)
        tail = order[heads[present] + size[present] - 1]
        rest = np.full(len(present), 255, np.uint8)
        inner = tail + 1 < len(bwt)
        rest[inner] = _range_minima(lcp, tail[inner] + 1, np.full(int(inner.sum()), len(bwt)))
        least = np.minimum(least, lcp.min())
        least[present] = rest
        last_fresh[present] = is_new[tail]
        seen += size
    take.close()
    return tuple(np.concatenate([o[k] for o in out]) if out else np.zeros(0, np.int64) for k in range(3))


def _merge(old, new, at, bwt, lcp, names, mend_at, mend_lcp, block):
    """Writes the next generation: old rows in order, new rows at their places, changed prefixes mended."""
    total, take = old.n + len(at), None
    for a in range(0, total, block):
        b = min(a + block, total)
        lo, hi = np.searchsorted(at, [a, b])
        stay = np.ones(b - a, bool)
        stay[at[lo:hi] - a] = False
        n = b - a - int(hi - lo)
        if take is None:
            take = old.blocks(n, 0, 1, 2)
            held_rows = next(take)
        else:
            held_rows = take.send(n) if n else [np.zeros(0, k) for _, k in _FILES]
        columns = []
        for held, fresh in zip(held_rows, (bwt, lcp, names)):
            col = np.empty(b - a, held.dtype)
            col[stay] = held
            col[~stay] = fresh[lo:hi]
            columns.append(col)
        lo, hi = np.searchsorted(mend_at, [a, b])
        columns[1][mend_at[lo:hi] - a] = mend_lcp[lo:hi]
        new.put(*columns)
    if take is not None:
        take.close()
    new.close()
    return new
