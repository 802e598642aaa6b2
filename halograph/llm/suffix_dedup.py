"""Removal of byte strings that already occur in an earlier document, on suffix order of the collection.

All windows of LENGTH bytes with the same smallest inner GRAM (their anchor) meet in one place, so the collection is
split by anchors: runs of neighbouring windows of one anchor are short strings, and the strings of a group of anchors
form a collection whose transform and common prefixes are built column by column. Windows are equal where the common
prefix reaches LENGTH; each then has the smallest identifier of the documents that hold it. Only anchors that occur
more than once, at any two places of the table, are looked at further. Where all strings of an anchor are the same, as
inside long copies, they have one smallest identifier and need no order; others are sent once from each chunk.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halograph.llm.column_bwt import MEMORY_ROWS, SHIFT, build
from halograph.llm.common import Scratch, mix, power_table, span_hashes

LENGTH, GRAM = 50, 28
REACH = LENGTH - GRAM + 1  # windows that can share an anchor in a row
CHUNK_BYTES = 4 << 20
SLICE_BYTES = 1 << 20
#: Bytes of text for each group of anchors.
GROUP_BYTES = 8 << 20
#: An anchor of more occurrences is dealt out by its windows instead, so that no group grows with one passage.
HEAVY = 20_000
_LARGEST = np.iinfo(np.int64).max


def _pack(a: np.ndarray) -> bytes:
    """Byte planes, compressed; rising numbers are sent as steps by the caller."""
    raw = np.ascontiguousarray(a.view(np.uint8).reshape(len(a), a.dtype.itemsize).T).tobytes()
    return len(a).to_bytes(8, "little") + pa.compress(raw, "zstd", asbytes=True) if len(a) else bytes(8)


def _unpack(b: bytes, kind) -> np.ndarray:
    n, size = int.from_bytes(b[:8], "little"), np.dtype(kind).itemsize
    if not n:
        return np.zeros(0, kind)
    planes = np.frombuffer(pa.decompress(b[8:], n * size, "zstd", asbytes=True), np.uint8).reshape(size, n)
    return np.ascontiguousarray(planes.T).reshape(-1).view(kind)


def _rising(a: np.ndarray) -> bytes:
    return _pack(np.diff(a, prepend=a.dtype.type(0)))


def _risen(b: bytes, kind) -> np.ndarray:
    return np.cumsum(_unpack(b, kind), dtype=kind)


def anchors(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(first window, number of windows, document, 48-bit hash of the anchor) of each run of windows of one anchor.

    While the smallest is looked for, places share a number with the hash and have its low 24 bits, so data is a slice
    below that (see _Chunk.parts)."""
    n = len(data)
    assert n <= 1 << 24
    none = np.zeros(0, np.int64)
    if n < LENGTH:
        return none, none, none, np.zeros(0, np.uint64)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * power_table(n), out=total[1:])
    name = mix((total[GRAM:] - total[:-GRAM]) * power_table(n + 1, True)[: n - GRAM + 1])
    key = (name & np.uint64(0xFFFFFFFFFF000000)) | np.arange(len(name), dtype=np.uint64)  # the leftmost of equals
    width = 1
    while 2 * width <= REACH:
        key = np.minimum(key[:-width], key[width:])
        width *= 2
    if width < REACH:
        key = np.minimum(key[: len(key) - (REACH - width)], key[REACH - width :])
    windows = n - LENGTH + 1
    key = key[:windows]
    sizes = np.diff(offsets)
    doc = np.repeat(np.arange(len(sizes)), np.maximum(sizes - LENGTH + 1, 0))
    inner = np.repeat(offsets[:-1] - np.concatenate([[0], np.cumsum(np.maximum(sizes - LENGTH + 1, 0))[:-1]]), np.maximum(sizes - LENGTH + 1, 0)) + np.arange(len(doc))
    key = key[inner]
    edge = np.ones(len(key), bool)
    edge[1:] = (key[1:] != key[:-1]) | (doc[1:] != doc[:-1])
    head = np.flatnonzero(edge)
    return inner[head], np.diff(np.append(head, len(key))), doc[head], name[(key[head] & np.uint64(0xFFFFFF)).astype(np.int64)] >> np.uint64(16)


def _chunks(batches):
    """Bounded chunks of documents: identifiers, ends and text, compressed."""
    from pyspark import TaskContext

    chunk = TaskContext.get().partitionId() << 32
    ids, data, ends, held = [], [], [], 0

    def out():
        joined = b"".join(data)
        have = [x is not None for x in ids]
        return pa.RecordBatch.from_arrays(
            [pa.array([chunk], pa.int64()), pa.array([len(joined)], pa.int64()), pa.array([_pack(np.array([x or 0 for x in ids], np.int64))], pa.binary())]
            + [pa.array([np.array(have, bool).tobytes()], pa.binary()), pa.array([_rising(np.array(ends, np.int64))], pa.binary()), pa.array([pa.compress(joined, "zstd", asbytes=True) if joined else b""], pa.binary())],
            names=["chunk", "size", "ids", "known", "ends", "text"],
        )

    for batch in batches:
        for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
            raw = (text.as_py() or "").encode()
            if ids and held + len(raw) > CHUNK_BYTES:
                yield out()
                chunk += 1
                ids, data, ends, held = [], [], [], 0
            ids.append(doc)
            data.append(raw)
            held += len(raw)
            ends.append(held)
    if ids:
        yield out()


class _Chunk:
    def __init__(self, row: dict):
        self.ids = _unpack(row["ids"], np.int64)
        self.known = np.frombuffer(row["known"], bool)
        self.offsets = np.concatenate([[0], _risen(row["ends"], np.int64)])
        self.data = np.frombuffer(pa.decompress(row["text"], row["size"], "zstd", asbytes=True), np.uint8) if row["size"] else np.zeros(0, np.uint8)

    def parts(self):
        """(first document, first byte, data, offsets) of slices of at most SLICE_BYTES windows. A longer text is cut into
        slices that overlap by LENGTH - 1 bytes, so each of its windows lies in one of them."""
        a, n = 0, len(self.ids)
        while a < n:
            b = max(a + 1, int(np.searchsorted(self.offsets, self.offsets[a] + SLICE_BYTES, "right")) - 1)
            low, high = int(self.offsets[a]), int(self.offsets[b])
            if high - low <= SLICE_BYTES:
                yield a, low, self.data[low:high], self.offsets[a : b + 1] - low
            else:
                for at in range(low, high - LENGTH + 1, SLICE_BYTES):
                    data = self.data[at : min(at + SLICE_BYTES + LENGTH - 1, high)]
                    yield a, at, data, np.array([0, len(data)])
            a = b

    def runs(self):
        """All runs of the chunk's documents with an identifier; places are bytes of the chunk."""
        found = []
        for a, low, data, offsets in self.parts():
            at, n, doc, h = anchors(data, offsets)
            keep = self.known[doc + a]
            found.append((at[keep] + low, n[keep], doc[keep] + a, h[keep]))
        return tuple(np.concatenate([f[k] for f in found]) for k in range(4)) if found else (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),)


def _dicts(batch):
    names = batch.schema.names
    for i in range(batch.num_rows):
        yield {n: batch.column(k)[i].as_py() for k, n in enumerate(names)}


def _strings(chunk: "_Chunk", at: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Hashes of the strings that runs of windows cover, slice by slice."""
    out = np.zeros(len(at), np.uint64)
    for a in range(0, len(at), 1 << 16):
        b = min(a + (1 << 16), len(at))
        low, high = at[a:b].min(), (at[a:b] + n[a:b] + LENGTH - 1).max()
        out[a:b] = span_hashes(chunk.data[low:high], at[a:b] - low, at[a:b] + n[a:b] + LENGTH - 1 - low)
    return out


def _split(group: np.ndarray, a: int = 4096):
    """(group, first, end) of the runs of a rising column, so many at a time: only groups that are there cost anything."""
    own, first = np.unique(group, return_index=True)
    ends = np.append(first[1:], len(group))
    for k in range(0, len(own), a):
        yield list(zip(own[k : k + a].tolist(), first[k : k + a].tolist(), ends[k : k + a].tolist()))


def _offer(groups: int):
    """The anchors of each chunk by group, a check of each distinct string at them, and the number of its runs."""

    def run(batches):
        for batch in batches:
            for row in _dicts(batch):
                chunk = _Chunk(row)
                at, n, _, h = chunk.runs()
                check = _strings(chunk, at, n) >> np.uint64(24)
                order = np.lexsort((check, h))
                h, check = h[order], check[order]
                edge = np.ones(len(h), bool)
                edge[1:] = (h[1:] != h[:-1]) | (check[1:] != check[:-1])
                head = np.flatnonzero(edge)
                n, h, check = np.diff(np.append(head, len(h))).astype(np.int32), h[head], check[head]
                group = (h % np.uint64(groups)).astype(np.int64)
                order = np.argsort(group, kind="stable")  # anchors keep rising inside a group
                group, n, h, check = group[order], n[order], h[order], check[order]
                for own in _split(group):
                    packed = [pa.array([f(x[a:b]) for _, a, b in own], pa.binary()) for f, x in ((_rising, h), (_pack, check), (_pack, n))]
                    yield pa.RecordBatch.from_arrays([pa.array([g for g, _, _ in own], pa.int32()), pa.array([row["chunk"]] * len(own), pa.int64()), *packed], names=["group", "chunk", "anchors", "checks", "runs"])

    return run


def _shared(heavy: int):
    """For each chunk those of its anchors that have more than one run in the whole table: with one string everywhere
    (single), with several, and, among these, with very many runs (heavy)."""

    def run(table: pa.Table) -> pa.Table:
        chunks = table.column("chunk").to_pylist()
        own = [_risen(b.as_py(), np.uint64) for b in table.column("anchors")]
        n = np.concatenate([_unpack(b.as_py(), np.int32) for b in table.column("runs")]).astype(np.int64)
        check = np.concatenate([_unpack(b.as_py(), np.uint64) for b in table.column("checks")])
        distinct, at = np.unique(np.concatenate(own), return_inverse=True)
        total = np.bincount(at, n, len(distinct))
        low, high = np.full(len(distinct), ~np.uint64(0)), np.zeros(len(distinct), np.uint64)
        np.minimum.at(low, at, check)
        np.maximum.at(high, at, check)
        several = (low != high)[at]
        cut = np.cumsum([0] + [len(x) for x in own])
        out = [[], [], []]
        for k, x in enumerate(own):
            t, more = total[at[cut[k] : cut[k + 1]]], several[cut[k] : cut[k + 1]]
            once = np.ones(len(x), bool)
            once[1:] = x[1:] != x[:-1]  # a chunk's anchors rise
            once &= t > 1
            for o, keep in zip(out, (once & ~more, once & more, once & (t > heavy) & more)):
                o.append(_rising(x[keep]))
        return pa.table([pa.array(chunks, pa.int64()), *(pa.array(o, pa.binary()) for o in out)], names=["chunk", "single", "several", "heavy"])

    return run


def _apart(data: np.ndarray, starts: np.ndarray, sizes: np.ndarray, first: np.ndarray, which: np.ndarray) -> np.ndarray:
    """Rows whose bytes are not those of the first row of their hash; firsts themselves need no look."""
    again = np.flatnonzero(first[which] != np.arange(len(which)))
    model = first[which[again]]
    same = sizes[again] == sizes[model]
    length = np.where(same, sizes[again], 0)
    differ = data[_spread(starts[again], length)] != data[_spread(starts[model], length)]
    odd = ~same
    if differ.any():
        odd[np.repeat(np.arange(len(again)), length)[differ]] = True
    return again[odd]


def _distinct(chunk: "_Chunk", at: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first run of each distinct string, which string each run covers, hash of each string); strings of one hash are told
    apart by their bytes. A string has one anchor, so equal strings meet."""
    if not len(at):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
    hashes = _strings(chunk, at, n)
    _, first, which = np.unique(hashes, return_index=True, return_inverse=True)
    for k in _apart(chunk.data, at, n + LENGTH - 1, first, which).tolist():  # of one hash but of other bytes
        which[k] = len(first)
        first = np.append(first, k)
    return first, which, hashes[first]


def _digests(chunk: "_Chunk", at: np.ndarray, n: np.ndarray) -> bytes:
    """64-bit keyed digests of strings, one after another: with the 48 bits of the anchor, chunks agree on a string by these."""
    data = memoryview(np.ascontiguousarray(chunk.data))
    return b"".join([hashlib.blake2b(data[a : a + m + LENGTH - 1], digest_size=8).digest() for a, m in zip(at.tolist(), n.tolist())])


def _member(x: np.ndarray, rising: np.ndarray) -> np.ndarray:
    if not len(rising):
        return np.zeros(len(x), bool)
    at = np.searchsorted(rising, x)
    at[at == len(rising)] = 0
    return rising[at] == x


def _send(groups: int):
    """What each chunk asks its groups (kinds of anchors apart), and, in group -1, where the answers belong."""

    def run(batches):
        for batch in batches:
            for row in _dicts(batch):
                chunk = _Chunk(row)
                single, several, heavy = (np.sort(np.concatenate([np.zeros(0, np.uint64)] + [_risen(x[k], np.uint64) for x in row["lists"]])) for k in ("single", "several", "heavy"))
                at, n, doc, h = chunk.runs()
                alike, differ = _member(h, single), _member(h, several)
                # single anchors: the anchor and a digest of the bytes name the string
                at1, n1, doc1, h1 = at[alike], n[alike], doc[alike], h[alike]
                first1, which1, _ = _distinct(chunk, at1, n1)
                anchor, least1 = h1[first1], np.full(len(first1), _LARGEST)
                np.minimum.at(least1, which1, chunk.ids[doc1])
                group1 = (mix(anchor) % np.uint64(groups)).astype(np.int64)
                order1 = np.lexsort((anchor, group1))
                rank1 = np.empty(len(order1), np.int64)
                rank1[order1] = np.arange(len(order1))
                at2, n2, doc2, h2 = at[differ], n[differ], doc[differ], h[differ]
                wide = _member(h2, heavy)
                if wide.any():  # each window on its own, dealt by its bytes
                    each = np.repeat(at2[wide] - np.concatenate([[0], np.cumsum(n2[wide])[:-1]]), n2[wide]) + np.arange(n2[wide].sum())
                    own = np.repeat(doc2[wide], n2[wide])
                    at2, doc2, n2 = np.concatenate([at2[~wide], each]), np.concatenate([doc2[~wide], own]), np.concatenate([n2[~wide], np.ones(len(each), np.int64)])
                    h2 = np.concatenate([h2[~wide], np.zeros(len(each), np.uint64)])
                first2, which2, name = _distinct(chunk, at2, n2)
                least2 = np.full(len(name), _LARGEST)
                np.minimum.at(least2, which2, chunk.ids[doc2])
                group2 = (np.where(h2[first2] > 0, mix(h2[first2]), name) % np.uint64(groups)).astype(np.int64)
                order2 = np.argsort(group2, kind="stable")
                rank2 = np.empty(len(order2), np.int64)
                rank2[order2] = np.arange(len(order2))
                # where: single ones first, then the others, each by document and place
                places = []
                for r, a, m, d in ((rank1[which1], at1, n1, doc1), (rank2[which2], at2, n2, doc2)):
                    o = np.lexsort((a, d))
                    places += [_pack(r[o].astype(np.uint32)), _pack(m[o].astype(np.uint8)), _pack(np.diff(a[o], prepend=0).astype(np.int32)), _pack(d[o].astype(np.uint32))]
                yield _sent([-1], [row["chunk"]], *[[x] for x in places])
                bounds = ({g: (a, b) for own in _split(x) for g, a, b in own} for x in (group1[order1], group2[order2]))
                cut1, cut2 = bounds
                present = sorted(cut1.keys() | cut2.keys())
                for base in range(0, len(present), 4096):
                    own = present[base : base + 4096]
                    cols = [[] for _ in range(8)]
                    for g in own:
                        (a1, b1), (a2, b2) = cut1.get(g, (0, 0)), cut2.get(g, (0, 0))
                        one, pick = order1[a1:b1], order2[a2:b2]
                        s, size = at2[first2[pick]], n2[first2[pick]] + LENGTH - 1
                        body = chunk.data[_spread(s, size)] if len(pick) else np.zeros(0, np.uint8)
                        bases = a1.to_bytes(8, "little") + a2.to_bytes(8, "little")
                        parts = (_rising(anchor[one]), _pack(least1[one]), _pack(name[pick]), _pack(size.astype(np.uint8)), _pack(least2[pick]), pa.compress(body.tobytes(), "zstd", asbytes=True) if len(body) else b"", bases, _digests(chunk, at1[first1[one]], n1[first1[one]]))
                        for c, v in zip(cols, parts):
                            c.append(v)
                    yield _sent(own, [row["chunk"]] * len(own), *cols)

    return run


_SENT = "group int, chunk long, " + ", ".join(f"{c} binary" for c in "abcdefgh")


def _sent(group, chunk, *binaries) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(group, pa.int32()), pa.array(chunk, pa.int64()), *(pa.array(x, pa.binary()) for x in binaries)], names=["group", "chunk", *"abcdefgh"])


def first_holders(data: np.ndarray, sizes: np.ndarray, least: np.ndarray, in_memory: int = MEMORY_ROWS) -> np.ndarray:
    """For every window of every string, the smallest identifier of any string that holds the same LENGTH bytes."""
    starts = np.concatenate([[0], np.cumsum(sizes)[:-1]]).astype(np.int64)
    windows = np.concatenate([[0], np.cumsum(sizes - LENGTH + 1)])
    _, lcp, names = build(data, starts, sizes, in_memory=in_memory)
    string, size = names // SHIFT, names % SHIFT
    real = np.flatnonzero(size >= LENGTH)
    holder = np.cumsum(lcp < LENGTH)[real]
    string, at = string[real].astype(np.int64), sizes[string[real]] - size[real]
    head = np.flatnonzero(np.diff(holder, prepend=-1))
    smallest = np.minimum.reduceat(least[string], head) if len(head) else np.zeros(0, np.int64)
    out = np.empty(windows[-1], np.int64)
    out[windows[string] + at] = np.repeat(smallest, np.diff(np.append(head, len(holder))))
    return out


def _smallest(names: list[np.ndarray], least: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(smallest of each name, first row of each, which name each row has)."""
    _, first, which = np.unique(np.concatenate(names), return_index=True, return_inverse=True)
    smallest = np.full(len(first), _LARGEST)
    np.minimum.at(smallest, which, least)
    return smallest, first, which


def _smallest_of_pairs(a: np.ndarray, b: np.ndarray, least: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(smallest of each distinct pair, which pair each row has)."""
    order = np.lexsort((b, a))
    edge = np.ones(len(a), bool)
    edge[1:] = (a[order][1:] != a[order][:-1]) | (b[order][1:] != b[order][:-1])
    which = np.empty(len(a), np.int64)
    which[order] = np.cumsum(edge) - 1
    head = np.flatnonzero(edge)
    return np.minimum.reduceat(least[order], head) if len(head) else np.zeros(0, np.int64), which


def _verified(name: np.ndarray, data: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Numbers of distinct strings: by name, and where bytes under one name differ, each row by itself."""
    _, first, which = np.unique(name, return_index=True, return_inverse=True)
    odd = _apart(data, starts, sizes, first, which)
    which[odd] = len(first) + np.arange(len(odd))
    return which


def _spread(begin: np.ndarray, n: np.ndarray) -> np.ndarray:
    """begin[0] .. begin[0] + n[0] - 1, begin[1] .. and so on."""
    return np.repeat(begin - np.concatenate([[0], np.cumsum(n)[:-1]])[: len(n)], n) + np.arange(n.sum())


def _group(table: pa.Table, in_memory: int = MEMORY_ROWS) -> pa.Table:
    """Answers of a group to every chunk: the smallest identifier for each single anchor, and for each window of a string."""
    col = {n: table.column(n).to_pylist() for n in ("chunk", *"abcdefgh")}
    anchor = [_risen(x, np.uint64) for x in col["a"]]
    digest = np.concatenate([np.frombuffer(d, np.uint64) for d in col["h"]])
    smallest1, which1 = _smallest_of_pairs(np.concatenate(anchor), digest, np.concatenate([_unpack(x, np.int64) for x in col["b"]]))
    name = [_unpack(x, np.uint64) for x in col["c"]]
    size = [_unpack(x, np.uint8).astype(np.int64) for x in col["d"]]
    data = np.concatenate([np.frombuffer(pa.decompress(x, int(s.sum()), "zstd", asbytes=True), np.uint8) if x else np.zeros(0, np.uint8) for x, s in zip(col["f"], size)])
    sizes = np.concatenate(size)
    starts = np.cumsum(sizes) - sizes
    smallest2, first, which2 = _smallest([_verified(np.concatenate(name), data, starts, sizes)], np.concatenate([_unpack(x, np.int64) for x in col["e"]]))
    s = sizes[first]
    holders = first_holders(data[_spread(starts[first], s)], s, smallest2, in_memory)
    windows = s - LENGTH + 1
    at = np.cumsum(windows) - windows
    cut1, cut2 = np.cumsum([0] + [len(x) for x in anchor]), np.cumsum([0] + [len(x) for x in name])
    one, many = [], []
    for k in range(len(name)):
        one.append(_pack(smallest1[which1[cut1[k] : cut1[k + 1]]]))
        own = which2[cut2[k] : cut2[k + 1]]
        many.append(_pack(holders[_spread(at[own], windows[own])]))
    return pa.table([pa.array(col["chunk"], pa.int64()), pa.array(col["g"], pa.binary()), pa.array(one, pa.binary()), pa.array(many, pa.binary())], names=["chunk", "base", "one", "many"])


def _covered(chunk: "_Chunk", row: dict) -> np.ndarray:
    gone = np.zeros(len(chunk.data) + 1, np.int32)
    if row["a"] is not None and row["groups"]:
        for kind, keys, at8 in (("one", "abcd", 0), ("many", "efgh", 8)):
            sid, n = _unpack(row[keys[0]], np.uint32).astype(np.int64), _unpack(row[keys[1]], np.uint8).astype(np.int64)
            at, doc = np.cumsum(_unpack(row[keys[2]], np.int32), dtype=np.int64), _unpack(row[keys[3]], np.uint32)
            if not len(sid):
                continue
            parts = sorted((int.from_bytes(g["base"][at8 : at8 + 8], "little"), k) for k, g in enumerate(row["groups"]))
            holders = np.concatenate([_unpack(row["groups"][k][kind], np.int64) for _, k in parts])
            if kind == "one":
                hit = np.flatnonzero(holders[sid] < chunk.ids[doc])
                np.add.at(gone, at[hit], 1)  # all windows of a run at once
                np.add.at(gone, at[hit] + n[hit] + LENGTH - 1, -1)
            else:
                width = np.zeros(int(sid.max()) + 1, np.int64)
                width[sid] = n
                begin = np.cumsum(width) - width
                place = _spread(at, n)
                hit = place[holders[_spread(begin[sid], n)] < np.repeat(chunk.ids[doc], n)]
                np.add.at(gone, hit, 1)
                np.add.at(gone, hit + LENGTH, -1)
    return np.cumsum(gone[:-1]) > 0


def _finish(texts: bool):
    def run(batches):
        for batch in batches:
            for row in _dicts(batch):
                chunk = _Chunk(row)
                covered = _covered(chunk, row)
                rows = []
                for k in range(len(chunk.ids)):
                    a, b = chunk.offsets[k], chunk.offsets[k + 1]
                    c = covered[a:b]
                    removed = int(c.sum())
                    kept = chunk.data[a:b][~c].tobytes() if removed else chunk.data[a:b].tobytes()
                    edges = np.flatnonzero(np.diff(c, prepend=False, append=False)) if removed else ()
                    spans = [{"start": int(x), "stop": int(y)} for x, y in zip(edges[::2], edges[1::2])]
                    rows.append((int(chunk.ids[k]) if chunk.known[k] else None, b - a, removed, len(spans), hashlib.sha256(kept).hexdigest(), spans, kept if texts else None))
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())])), pa.binary())
                names = ("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans", "kept")
                yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], names=names)

    return run


def suffix_dedup(docs: DataFrame, *, texts: bool = True, heavy: int = HEAVY, in_memory: int = MEMORY_ROWS, scratch: Scratch | None = None) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans, kept for every row.

    A byte goes if it lies in a window of 50 bytes that also starts in a document with a smaller doc_id; all windows are
    judged on the input. ``kept`` (what is left; null without ``texts``) may end inside a letter. A null text is empty,
    texts under 50 bytes are whole. Rows of one doc_id do not remove from each other; a row without doc_id neither
    removes nor loses anything. Other columns are not read; an empty table gives an empty result. Collections of a group
    of anchors over ``in_memory`` suffixes are ordered through files of the task, smaller ones in memory.
    """
    scratch = scratch or Scratch(docs.sparkSession)
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("text"))
    chunks = scratch.keep_bucketed(source.mapInArrow(_chunks, "chunk long, size long, ids binary, known binary, ends binary, text binary"), "chunks", "chunk")
    groups = int((chunks.agg(F.sum("size")).first()[0] or 0) // GROUP_BYTES) + 1
    offered = chunks.mapInArrow(_offer(groups), "group int, chunk long, anchors binary, checks binary, runs binary")
    shared = offered.groupBy("group").applyInArrow(_shared(heavy), "chunk long, single binary, several binary, heavy binary")
    lists = shared.groupBy("chunk").agg(F.collect_list(F.struct("single", "several", "heavy")).alias("lists"))  # at most the anchors of a chunk
    sent = scratch.keep(chunks.join(lists, "chunk").mapInArrow(_send(groups), _SENT), "sent")
    holders = sent.filter("group >= 0").groupBy("group").applyInArrow(lambda t: _group(t, in_memory), "chunk long, base binary, one binary, many binary")
    per_chunk = holders.groupBy("chunk").agg(F.collect_list(F.struct("base", "one", "many")).alias("groups"))
    whole = chunks.join(sent.filter("group < 0").drop("group"), "chunk", "left").join(per_chunk, "chunk", "left")
    return whole.mapInArrow(_finish(texts), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<struct<start:long,stop:long>>, kept binary")


def op3_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    out = suffix_dedup(spark.read.parquet(f"{sf_dir}/documents.parquet"), texts=False)
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


OP3_SQL = """
WITH bytes AS (SELECT doc_id, encode(coalesce(text, '')) AS b, strlen(coalesce(text, '')) AS n FROM documents),
windows AS (SELECT doc_id, p, b[p:p + 49] AS w FROM (SELECT doc_id, b, unnest(range(1, n - 48)) AS p FROM bytes WHERE n >= 50)),
firsts AS (SELECT w, min(doc_id) AS least FROM windows GROUP BY w),
gone AS (SELECT doc_id, p, CASE WHEN p > lag(p) OVER (PARTITION BY doc_id ORDER BY p) + 50 OR lag(p) OVER (PARTITION BY doc_id ORDER BY p) IS NULL THEN 1 ELSE 0 END AS cut FROM windows JOIN firsts USING (w) WHERE least < doc_id),
spans AS (SELECT doc_id, min(p) AS a, max(p) + 49 AS z FROM (SELECT *, sum(cut) OVER (PARTITION BY doc_id ORDER BY p) AS run FROM gone) GROUP BY doc_id, run),
kept AS (
  SELECT doc_id, a AS stop, coalesce(lag(z) OVER (PARTITION BY doc_id ORDER BY a), 0) + 1 AS start FROM spans
  UNION ALL SELECT doc_id, n + 1, coalesce((SELECT max(z) FROM spans s WHERE s.doc_id = t.doc_id), 0) + 1 FROM bytes t),
left_over AS (SELECT doc_id, from_hex(string_agg(hex(b[start:stop - 1]), '' ORDER BY start)) AS k FROM kept JOIN bytes USING (doc_id) WHERE stop > start GROUP BY doc_id)
SELECT t.doc_id, CAST(n AS BIGINT) AS n_bytes, CAST(coalesce((SELECT sum(z - a + 1) FROM spans s WHERE s.doc_id = t.doc_id), 0) AS BIGINT) AS n_removed,
  (SELECT count(*) FROM spans s WHERE s.doc_id = t.doc_id) AS n_spans, sha256(coalesce(k, ''::BLOB)) AS kept_sha256
FROM bytes t LEFT JOIN left_over USING (doc_id)
"""
