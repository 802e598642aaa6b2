"""Benchmark decontamination by pigeonhole edit matching.

An item of n characters may differ by ``rate * n`` edits, its budget. Cut into budget + 1 pieces, at least one piece of
an item within budget stands in the document unchanged, so looking up all pieces finds every candidate. Candidate
windows are verified by bit-parallel edit distance with free ends in the document.
"""

from __future__ import annotations

import re
import uuid
from bisect import bisect_right

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from halograph.llm.common import ascii_lower, slices, worker_store

#: Edits allowed for each character of an item.
RATE = 0.08
#: Benchmark text that is looked for at once; a larger benchmark is searched in blocks of about this size.
BLOCK_BYTES = 8 << 20
_HIT = "doc_id long, item string, distance int, start long, stop long"


def normalise(text: str) -> bytes:
    """UTF-8 with A-Z lower-cased, each run of ASCII white space one space, none at the ends."""
    return b" ".join(text.encode().lower().split())


def pieces(item: bytes, rate: float = RATE) -> list[tuple[int, bytes]]:
    """(offset, piece) of an item's budget + 1 pieces, as equal in length as can be."""
    k = int(len(item) * rate)
    cut = [len(item) * i // (k + 1) for i in range(k + 2)]
    return [(a, item[a:b]) for a, b in zip(cut, cut[1:]) if b > a]


def masks(pattern: bytes) -> dict[int, int]:
    at: dict[int, int] = {}
    for i, c in enumerate(pattern):
        at[c] = at.get(c, 0) | 1 << i
    return at


def best_match(at: dict[int, int], m: int, text: bytes, most: int) -> tuple[int, int] | None:
    """(distance, end) of the best place of the pattern in text, the first of equals; None beyond ``most``.

    Vertical differences of the edit matrix are held as two bit vectors; a step takes a few word operations.
    """
    full, top = (1 << m) - 1, 1 << (m - 1)
    plus, minus, score = full, 0, m
    best = None
    get = at.get
    for j, c in enumerate(text, 1):
        eq = get(c, 0)
        diagonal = (((eq & plus) + plus) ^ plus) | eq | minus
        up = minus | (full & ~(diagonal | plus))
        down = plus & diagonal
        if up & top:
            score += 1
        elif down & top:
            score -= 1
        up = up << 1 & full
        down = down << 1 & full
        plus = down | (full & ~(diagonal | up))
        minus = up & diagonal
        if score <= most and (best is None or score < best[0]):
            best = (score, j)
    return best


class Matcher:
    """Finds the items of a benchmark block in documents.

    Every place of a text is a window of HEAD bytes read as a number. A bit table passes the windows that may begin a
    piece, a sorted list of piece heads decides, and whole pieces are compared last. Pieces shorter than a window occur
    only in items shorter than two pieces; those are looked for one by one. Windows that share too few grams
    with the item are passed over before the distance is computed.
    """

    HEAD, BITS, GRAM = 8, 20, 4

    def __init__(self, items: list[str], rate: float):
        self.items = list(dict.fromkeys(n for t in items if (n := normalise(t or ""))))  # an item is its text here, not its id
        self.rate, self.masks = rate, {}
        owners: dict[bytes, dict[bytes, list[tuple[int, int]]]] = {}
        self.short: list[tuple[bytes, int, int]] = []
        for i, n in enumerate(self.items):
            for offset, piece in pieces(n, rate):
                if len(piece) < self.HEAD:
                    self.short.append((piece, i, offset))
                else:
                    owners.setdefault(piece[: self.HEAD], {}).setdefault(piece, []).append((i, offset))
        heads = np.frombuffer(b"".join(owners), "<u8")
        order = np.argsort(heads)
        self.heads = heads[order]
        groups = list(owners.values())
        self.groups = [list(groups[k].items()) for k in order]
        self.table = np.zeros(1 << self.BITS, bool)
        self.table[self._slot(self.heads)] = True

    def _slot(self, windows: np.ndarray) -> np.ndarray:
        return (windows * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.BITS)

    def _windows(self, data: np.ndarray) -> np.ndarray:
        pairs = data[:-1].astype(np.uint16) | data[1:].astype(np.uint16) << np.uint16(8)
        fours = pairs[:-2].astype(np.uint32) | pairs[2:].astype(np.uint32) << np.uint32(16)
        return fours[:-4].astype(np.uint64) | fours[4:].astype(np.uint64) << np.uint64(32)

    def find_all(self, texts: list[str]) -> list[tuple[int, int, int, int, int]]:
        """(text number, item number, distance, start, stop) of each item's best match, as bytes of the UTF-8 text."""
        docs = [normalise(t) for t in texts]
        joined = b"\n".join(docs)
        starts = np.cumsum([0] + [len(d) + 1 for d in docs])
        seen: dict[tuple[int, int], set[int]] = {}
        if len(joined) >= self.HEAD and len(self.heads):
            windows = self._windows(np.frombuffer(joined, np.uint8))
            at = np.flatnonzero(self.table[self._slot(windows)])
            place = np.searchsorted(self.heads, windows[at])
            real = self.heads[np.minimum(place, len(self.heads) - 1)] == windows[at]
            at, place = at[real], place[real]
            for i, g, d in zip(at.tolist(), place.tolist(), (np.searchsorted(starts, at, "right") - 1).tolist()):
                for piece, own in self.groups[g]:
                    if joined.startswith(piece, i):
                        for item, offset in own:
                            seen.setdefault((d, item), set()).add(i - int(starts[d]) - offset)
        for piece, item, offset in self.short:
            for d, doc in enumerate(docs):
                i = doc.find(piece)
                while i >= 0:
                    seen.setdefault((d, item), set()).add(i - offset)
                    i = doc.find(piece, i + 1)
        found = []
        for (d, item), places in seen.items():
            if best := self._verify(docs[d], item, sorted(places)):
                distance, stop = best
                m = len(self.items[item])
                start = max(0, stop - m - int(m * self.rate))
                found.append((d, item, distance, *self._span(texts[d].encode(), start, stop)))
        return found

    def _verify(self, doc: bytes, item: int, places: list[int]) -> tuple[int, int] | None:
        pattern = self.items[item]
        m, k = len(pattern), int(len(pattern) * self.rate)
        at = self.masks.get(item)
        if at is None:
            at = self.masks[item] = masks(pattern)
        best, i = None, 0
        while i < len(places):
            first = last = places[i]
            while i < len(places) and places[i] <= last + 2 * k + 1:
                last = places[i]
                i += 1
            low = max(0, first - k)
            window = doc[low : last + m + k]
            if len(window) >= m - k and self._shares(item, window, m - self.GRAM + 1 - k * self.GRAM) and (got := best_match(at, m, window, k)) and (best is None or got[0] < best[0]):
                best = (got[0], low + got[1])
        return best

    def _shares(self, item: int, window: bytes, least: int) -> bool:
        """Whether enough grams of the item stand in the window: an edit spoils at most GRAM of them, so no match is lost."""
        if least <= 0:
            return True
        q, there = self.GRAM, self.items[item]
        grams = {window[i : i + q] for i in range(len(window) - q + 1)}
        return sum([there[i : i + q] in grams for i in range(len(there) - q + 1)]) >= least

    @staticmethod
    def _span(text: bytes, a: int, b: int) -> tuple[int, int]:
        """The place in the text of normalised offsets a to b, widened to whole words."""
        heads, starts, ends, n = [], [], [], 0
        for w in re.finditer(rb"[^\x20\x09-\x0D]+", text):
            heads.append(n)
            starts.append(w.start())
            ends.append(w.end())
            n += w.end() - w.start() + 1
        return starts[max(0, bisect_right(heads, a) - 1)], ends[max(0, bisect_right(heads, b - 1) - 1)]


def _blocks(benchmark: DataFrame, rate: float, block_bytes: int) -> list:
    """Broadcasts of the distinct normalised texts of a benchmark, numbered by text: no text is in two blocks, so a
    block holds about ``block_bytes`` however often an item is repeated."""
    spark = benchmark.sparkSession
    texts = benchmark.select(normal_text(F.col("text")).alias("text")).filter("text <> ''").distinct()
    total = texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = int(total // block_bytes) + 1
    for b in range(n):
        part = texts.filter(F.pmod(F.xxhash64("text"), F.lit(n)) == b) if n > 1 else texts
        yield spark.sparkContext.broadcast(([r.text for r in part.collect()], rate))


def normal_text(text: Column) -> Column:
    """What ``normalise`` does, as a column: equal items meet by it."""
    return F.coalesce(F.trim(F.regexp_replace(ascii_lower(text), r"[\x20\x09-\x0D]+", " ")), F.lit(""))


def contaminated(docs: DataFrame, benchmark: DataFrame, *, rate: float = RATE, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, item_id, distance, start, stop for every document and item within the edit budget of each other.

    Letters A-Z match in either case and all white space is alike. ``start`` and ``stop`` bound the match in the UTF-8
    text of the document, to whole words; of equal matches the first. A null or blank text or item matches nothing; an
    item_id or doc_id may be null. Repeated documents give repeated rows, repeated items (same id and text) count once;
    different texts of one id, or without id, are items of their own. Other columns are not read, empty tables give no
    rows, texts of any length are searched whole. The benchmark is a query set: its texts are read in blocks of about
    ``block_bytes`` (a longer item is a block of its own), and each block is searched for in all documents.
    """
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("text"))
    found = None
    for shared in _blocks(benchmark, rate, block_bytes):
        hits = source.mapInArrow(_search(shared), _HIT)
        found = hits if found is None else found.unionByName(hits)
    names = benchmark.select(F.col("item_id").cast("long").alias("item_id"), normal_text(F.col("text")).alias("item")).distinct()
    return found.join(names, "item").select("doc_id", "item_id", "distance", "start", "stop")


def _matcher(key: str, shared) -> Matcher:
    store = worker_store("matcher")
    if key not in store:
        if len(store) >= 2:  # blocks are searched one after another
            store.clear()
        store[key] = Matcher(*shared.value)
    return store[key]


def _search(shared):
    key = uuid.uuid4().hex

    def run(batches):
        matcher = _matcher(key, shared)
        kinds = (pa.int64(), pa.string(), pa.int32(), pa.int64(), pa.int64())
        for batch in batches:
            for part in slices(batch, "text", 4 << 20):
                ids = part.column(0).to_pylist()
                out = [(ids[d], matcher.items[item].decode(), *hit) for d, item, *hit in matcher.find_all([t.as_py() or "" for t in part.column(1)])]
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, t in enumerate(kinds)], names=["doc_id", "item", "distance", "start", "stop"])

    return run


def _clean(shared):
    key = uuid.uuid4().hex

    def run(batches):
        matcher = _matcher(key, shared)
        for batch in batches:
            for part in slices(batch, "text", 4 << 20):
                texts = part.column(part.schema.get_field_index("text"))
                bad = {d for d, *_ in matcher.find_all([t.as_py() or "" for t in texts])}
                yield part.filter(pa.array([d not in bad for d in range(part.num_rows)], pa.bool_()))

    return run


def decontaminate(docs: DataFrame, benchmark: DataFrame, *, rate: float = RATE, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The rows, all columns, that hold no benchmark item. Each row is judged by its own text where it lies, so rows that
    share a doc_id, or have none, do not share a verdict, no row is shuffled and column names cannot clash."""
    for shared in _blocks(benchmark, rate, block_bytes):
        docs = docs.mapInArrow(_clean(shared), docs.schema)
    return docs


def op10_decontaminate(spark, sf_dir: str) -> DataFrame:
    return contaminated(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
