"""Near-duplicates by SetSketch registers, banding, joint likelihood and verification on full sets.

A register is the logarithm, to a base slightly over 1, of the smallest hash of a document's shingles, rounded to a whole
number: exponentially spaced, cut at both ends, merged by the maximum. Two documents share a register about as often as
their sets overlap, so groups of registers (bands) bring candidates together. Larger, smaller and equal registers of a
pair, with the set sizes, give the likelihood of its Jaccard similarity; pairs that are far below the threshold are
left, all others are decided on the full shingle sets. Documents of equal sets are one class throughout.

No pairs of a bucket are listed. The classes of a bucket gather at the least of them, its lead, and a lead's classes
are searched together, in blocks of bounded size: one class after another that is not yet joined to the lead is held
against all the rest, and links that join anything new come out. Classes of different blocks that are not of the lead's
component are then held against the other blocks, so every link between different components of a bucket is found.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halograph.llm.common import LOWER_BYTES, WORD_BREAK, Scratch, mix, runs, slices, span_hashes, text_bytes
from halograph.llm.components import components

SHINGLE = 5
#: A pair of similarity 0.75 shares none of 52 bands of 5 registers with probability below 1e-6.
BANDS, ROWS = 52, 5
REGISTERS = BANDS * ROWS
BASE = 1.001
#: Registers run from 0 to LIMIT.
LIMIT = 40_000
#: Pairs whose likeliest similarity is this far below the threshold are left: over six deviations of the estimate.
MARGIN = 0.18
#: Classes of one lead that are searched together, and the shingles that they may have between them, about.
BLOCK, BLOCK_SHINGLES = 1024, 1 << 19
#: Shingles that are looked up at once.
LOOK = 1 << 19
#: Places that the classes of one lead are dealt to while they are looked up.
SALTS = 64
#: Places of the filter by which rows are passed over before their texts are moved: 4 MB, in pieces of PIECE places.
PLACES, PIECE = 1 << 25, 1 << 15
#: Words beyond so many bytes are hashed by a digest.
LONG_WORD = 64
SLICE_BYTES = 1 << 20

_rng = np.random.default_rng(20240607)
_FLIP = _rng.integers(0, 1 << 32, REGISTERS, dtype=np.uint32)
_ODD = _rng.integers(0, 1 << 31, REGISTERS, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
_STEP = [np.uint64(x | 1) for x in _rng.integers(0, 1 << 63, SHINGLE, dtype=np.uint64).tolist()]


def shingle_sets(data: np.ndarray, offsets: np.ndarray) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingle hashes of each text; words are runs of bytes other than ASCII white space."""
    starts, ends, doc = runs(WORD_BREAK[data], offsets)
    words = span_hashes(LOWER_BYTES[data], starts, ends, LONG_WORD)
    n = len(offsets) - 1
    cut = np.searchsorted(doc, np.arange(n + 1))
    grams = np.zeros(max(0, len(words) - SHINGLE + 1), np.uint64)
    for j in range(SHINGLE):
        grams += words[j : j + len(grams)] * _STEP[j]
    grams = mix(grams)
    out = []
    for a, b in zip(cut[:-1].tolist(), cut[1:].tolist()):
        if b - a >= SHINGLE:
            out.append(np.unique(grams[a : b - SHINGLE + 1]))
        elif b > a:
            whole = np.array([b - a], np.uint64)
            for w in words[a:b]:
                whole = mix(whole * _STEP[0] + w)
            out.append(whole)
        else:
            out.append(np.zeros(0, np.uint64))
    return out


_WORD = re.compile(rb"[^\x20\x09-\x0D]+")
_LOWER = bytes(LOWER_BYTES)


def word_shingles(text: str) -> set[bytes]:
    """The shingles themselves, by which links are confirmed."""
    words = _WORD.findall(text.encode().translate(_LOWER))
    return {b" ".join(words[i : i + SHINGLE]) for i in range(max(1, len(words) - SHINGLE + 1))} if words else set()


def confirmed(a: set[bytes], b: set[bytes], percent: int) -> bool:
    both = len(a & b)
    return 100 * both >= percent * (len(a) + len(b) - both)


def set_digest(shingles: np.ndarray) -> bytes:
    return hashlib.blake2b(shingles.tobytes(), digest_size=16).digest()


def registers(shingles: np.ndarray) -> np.ndarray:
    """The sketch of a set; registers of a union are the larger of the two."""
    least = np.full(REGISTERS, 0xFFFFFFFF, np.uint32)
    low = (shingles >> np.uint64(32)).astype(np.uint32)
    for a in range(0, len(low), 2048):
        part = low[a : a + 2048]
        np.minimum(least, ((part[None, :] ^ _FLIP[:, None]) * _ODD[:, None]).min(1), out=least)
    u = (least.astype(np.float64) + 0.5) / 4294967296.0
    return np.clip(np.floor(1 - np.log(-np.log1p(-u)) / np.log(BASE)) + 4000, 0, LIMIT).astype(np.uint16) if len(shingles) else np.zeros(REGISTERS, np.uint16)


def band_keys(sketches: np.ndarray) -> np.ndarray:
    """One 64-bit key for each band of each row of sketches."""
    rows = sketches.astype(np.uint64).reshape(-1, BANDS, ROWS)
    key = np.broadcast_to(np.arange(1, BANDS + 1, dtype=np.uint64), rows.shape[:2]).copy()
    for j in range(ROWS):
        key = mix(key * np.uint64(0x9E3779B97F4A7C15) + rows[:, :, j])
    return key


def likeliest_similarity(a: np.ndarray, b: np.ndarray, na: np.ndarray, nb: np.ndarray) -> np.ndarray:
    """Jaccard similarity of greatest likelihood for each pair of sketches with known set sizes."""
    more, less = (a > b).sum(1), (a < b).sum(1)
    same = a.shape[1] - more - less
    u = na / (na + nb)
    v = 1 - u
    grid = np.linspace(0, 1, 101)[None, :] * np.minimum(u / v, v / u)[:, None]
    p = lambda x: -np.log1p(-np.clip(x, 1e-12, 1) * (BASE - 1) / BASE) / np.log(BASE)
    up, down = p(u[:, None] - v[:, None] * grid), p(v[:, None] - u[:, None] * grid)
    value = more[:, None] * np.log(up) + less[:, None] * np.log(down) + same[:, None] * np.log(np.maximum(1 - up - down, 1e-12))
    return np.take_along_axis(grid, value.argmax(1)[:, None], 1)[:, 0]


def _sketch(batches):
    for batch in batches:
        for part in slices(batch, "text", SLICE_BYTES):
            sets = shingle_sets(*text_bytes(part.column(1)))
            digest = [set_digest(s) for s in sets]
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array(digest, pa.binary()), pa.array([registers(s).tobytes() for s in sets], pa.binary())],
                names=["doc_id", "n", "digest", "sketch"],
            )


def _bands(batches):
    for batch in batches:
        sketches = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint16).reshape(-1, REGISTERS)
        ids = np.repeat(batch.column(0).to_numpy(zero_copy_only=False), BANDS)
        yield pa.RecordBatch.from_arrays([pa.array(band_keys(sketches).ravel().view(np.int64)), pa.array(ids)], names=["key", "id"])


def _star(batches):
    """lead, id for rows sorted by key and id: every class of a band's bucket with the first, across batches too."""
    key = lead = None
    for batch in batches:
        if not batch.num_rows:
            continue
        k, i = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        head = np.flatnonzero(np.diff(k, prepend=k[0] - 1))
        leads = np.repeat(i[head], np.diff(np.append(head, len(k))))
        if key is not None and k[0] == key:
            leads[: head[1] if len(head) > 1 else len(k)] = lead
        key, lead = int(k[-1]), int(leads[-1])
        other = leads != i
        pairs = np.unique(np.stack([leads[other], i[other]], 1), axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["lead", "id"])


def _likely(x: np.ndarray, n: int, sketches: np.ndarray, sizes: np.ndarray, percent: int) -> np.ndarray:
    """Which of the classes class x (its sketch and set size) may be linked with: by size, then by likelihood."""
    near = np.flatnonzero(100 * np.minimum(sizes, n) >= percent * np.maximum(sizes, n))
    if not len(near):
        return near
    guess = likeliest_similarity(np.broadcast_to(x, (len(near), REGISTERS)), sketches[near], np.full(len(near), float(n)), sizes[near].astype(np.float64))
    return near[guess >= percent / 100 - MARGIN]


class _Block:
    """Classes that are searched together: their sets as numbered shingles, their sketches and texts."""

    def __init__(self, ids: list[int], sets: list[np.ndarray], sketches: list[bytes], texts: list[str], percent: int):
        self.ids, self.texts, self.percent = ids, texts, percent
        self.size = np.array([len(s) for s in sets], np.int64)
        self.start = np.cumsum(self.size) - self.size
        distinct, flat = np.unique(np.concatenate(sets), return_inverse=True)
        self.flat, self.mark = flat.astype(np.uint32), np.zeros(len(distinct) + 1, bool)
        self.sketch = np.frombuffer(b"".join(sketches), np.uint16).reshape(-1, REGISTERS)

    def linked(self, x: int, others: np.ndarray) -> list[int]:
        """Those of the others that class x is linked with."""
        others = others[_likely(self.sketch[x], int(self.size[x]), self.sketch[others], self.size[others], self.percent)]
        if not len(others):
            return []
        own = self.flat[self.start[x] : self.start[x] + self.size[x]]
        self.mark[own] = True
        close = []
        ends = np.cumsum(self.size[others])
        cuts = np.searchsorted(ends, np.arange(LOOK, ends[-1] + LOOK, LOOK), "right")
        for some in np.split(others, np.unique(cuts[cuts < len(others)])):
            n = self.size[some]
            if len(n):
                at = np.repeat(self.start[some] - (np.cumsum(n) - n), n) + np.arange(n.sum())
                both = np.add.reduceat(self.mark[self.flat[at]], np.cumsum(n) - n, dtype=np.int64)
                close += some[100 * both >= self.percent * (self.size[x] + n - both)].tolist()
        self.mark[own] = False
        if not close:
            return []
        words = word_shingles(self.texts[x])
        return [y for y in close if confirmed(words, word_shingles(self.texts[y]), self.percent)]

    def join(self, component: list[int]) -> list[tuple[int, int]]:
        """Links that join components: the first class and whatever is not joined to it are held against all others."""
        parent: dict[int, int] = {}

        def root(c: int) -> int:
            while parent.get(c, c) != c:
                c = parent[c]
            return c

        found = []
        for x in range(len(self.ids)):
            if x and root(component[x]) == root(component[0]):
                continue
            mine = root(component[x])
            rest = np.array([y for y in range(len(self.ids)) if y != x and root(component[y]) != mine], np.int64)
            for y in self.linked(x, rest) if len(rest) else ():
                a, b = root(component[x]), root(component[y])
                if a != b:
                    parent[max(a, b)] = min(a, b)
                    found.append((self.ids[x], self.ids[y]))
        return found


def _sets_of(texts: list[str]) -> list[np.ndarray]:
    sets, a = [], 0
    while a < len(texts):
        b, held = a, 0
        while b < len(texts) and (b == a or held < SLICE_BYTES):
            held += len(texts[b])
            b += 1
        sets += shingle_sets(*text_bytes(pa.array(texts[a:b], pa.large_string())))
        a = b
    return sets


def _pairs(found) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([f[k] for f in found], pa.int64()) for k in (0, 1)], names=["a", "b"])


def _grouped(batches, n_keys: int):
    """(key, rows) of rows that are sorted by their first columns, also across batches."""
    now, rows = None, []
    for batch in batches:
        keys = list(zip(*(batch.column(k).to_pylist() for k in range(n_keys))))
        for i, key in enumerate(keys):
            if key != now:
                if rows:
                    yield now, rows
                now, rows = key, []
            rows.append(tuple(batch.column(k)[i].as_py() for k in range(n_keys, batch.num_columns)))
    if rows:
        yield now, rows


def _search(percent: int):
    """Links among the classes of each block (lead, block; id, text, digest, sketch), at most BLOCK classes and the lead."""

    def run(batches):
        for (lead, _), rows in _grouped(batches, 2):
            rows.sort(key=lambda r: (r[0] != lead, r[0]))
            sets = _sets_of([r[1] or "" for r in rows])
            # a doc_id may stand for several texts: the one of the class's set is meant
            real = [k for k, r in enumerate(rows) if set_digest(sets[k]) == r[2] and (k == 0 or rows[k - 1][0] != r[0] or set_digest(sets[k - 1]) != r[2])]
            if len(real) > 1:
                block = _Block([rows[k][0] for k in real], [sets[k] for k in real], [rows[k][3] for k in real], [rows[k][1] or "" for k in real], percent)
                yield _pairs(block.join(list(block.ids)))

    return run


def _guess(percent: int):
    """Pairs of other components that may be linked, by sketches: rows (lead, block, part; id, component, pivot, n, sketch),
    of which the pivots are held against the others."""

    def run(batches):
        for _, rows in _grouped(batches, 3):
            pivots, others = [r for r in rows if r[2]], [r for r in rows if not r[2]]
            if not pivots or not others:
                continue
            sketches = np.frombuffer(b"".join(r[4] for r in others), np.uint16).reshape(-1, REGISTERS)
            sizes, component = np.array([r[3] for r in others]), np.array([r[1] for r in others])
            for p in pivots:
                rest = np.flatnonzero(component != p[1])
                near = rest[_likely(np.frombuffer(p[4], np.uint16), p[3], sketches[rest], sizes[rest], percent)]
                yield _pairs([(min(p[0], others[y][0]), max(p[0], others[y][0])) for y in near.tolist()])

    return run


def _verify(percent: int):
    def run(batches):
        for batch in batches:
            a, b, own, other = (batch.column(k) for k in range(4))
            yield _pairs([(a[i].as_py(), b[i].as_py()) for i in range(batch.num_rows) if confirmed(word_shingles(own[i].as_py() or ""), word_shingles(other[i].as_py() or ""), percent)])

    return run


def _matching(batches):
    """id, text of rows (id, text, digest) whose text has the set of that digest."""
    for batch in batches:
        for part in slices(batch, "text", SLICE_BYTES):
            right = [set_digest(x) == d.as_py() for x, d in zip(shingle_sets(*text_bytes(part.column(1))), part.column(2))]
            yield part.select(["id", "text"]).filter(pa.array(right, pa.bool_()))


def _marked(marks: np.ndarray):
    """Rows (place, doc_id, text) whose place is marked, without the place."""

    def run(batches):
        for batch in batches:
            at = batch.column(0).to_numpy()
            there = (marks[at >> 3] >> (at & 7).astype(np.uint8)) & 1
            yield batch.select(["doc_id", "text"]).filter(pa.array(there.astype(bool)))

    return run


class NearDuplicates:
    """The steps of the search over one table; ``result`` is what near_dedup returns."""

    def __init__(self, docs: DataFrame, percent: int, scratch: Scratch):
        self.percent, self.scratch, keep = percent, scratch, scratch.keep
        self.source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("text"))
        self.sets = keep(self.source.mapInArrow(_sketch, "doc_id long, n long, digest binary, sketch binary"), "sketches")
        real = self.sets.filter("n > 0 AND doc_id IS NOT NULL")
        # A class has a number of its own: documents that share a doc_id may be of different classes.
        numbered = real.groupBy("digest").agg(F.min("doc_id").alias("least")).withColumn("id", F.monotonically_increasing_id())
        self.classes = keep(numbered, "classes")
        owner = self.classes.withColumnRenamed("least", "doc_id")
        self.models = keep(real.join(owner, ["digest", "doc_id"]).groupBy("id").agg(F.first("doc_id").alias("doc_id"), F.first("n").alias("n"), F.first("digest").alias("digest"), F.first("sketch").alias("sketch")), "models")

    def stars(self) -> DataFrame:
        """lead, id: classes that share a band, with the least class of its bucket."""
        bands = self.models.select("id", "sketch").mapInArrow(_bands, "key long, id long")
        return bands.repartition("key").sortWithinPartitions("key", "id").mapInArrow(_star, "lead long, id long").distinct()

    def among(self, doc_ids: DataFrame) -> DataFrame:
        """The rows of the source that have one of these doc_ids, and a few more: a filter of bounded size sorts out most of
        the others where they lie. A join has to follow; the more doc_ids, the more rows it leaves to that."""
        place = F.pmod(F.xxhash64("doc_id"), F.lit(PLACES)).cast("long")
        pieces = doc_ids.select(place.alias("p")).groupBy(F.call_function("div", F.col("p"), F.lit(PIECE)).alias("piece")).agg(F.bitmap_construct_agg(F.pmod(F.col("p"), F.lit(PIECE))).alias("bits"))
        marks = np.zeros((PLACES // PIECE, PIECE // 8), np.uint8)
        for piece, bits in pieces.collect():  # a row of 4 KB for each piece
            marks[piece] = np.frombuffer(bits, np.uint8)
        return self.source.select(place.alias("place"), "doc_id", "text").mapInArrow(_marked(marks.ravel()), "doc_id long, text string")

    def texts(self, ids: DataFrame) -> DataFrame:
        """id, text, digest of classes; where a doc_id stands for several texts, all of them."""
        wanted = self.scratch.keep(ids.join(self.models.select("id", F.col("doc_id").alias("_doc"), "digest"), "id"), "wanted")
        source = self.among(wanted.select(F.col("_doc").alias("doc_id")))
        return source.join(wanted, source.doc_id == wanted["_doc"]).select("id", "text", "digest")

    def second_look(self, members: DataFrame, found: DataFrame) -> DataFrame | None:
        """Links between blocks of one lead, for classes that are not of the lead's component; None where there are none."""
        keep, percent = self.scratch.keep, self.percent
        named = lambda df, c: df.join(found.select(F.col("node").alias(c), F.col("component").alias(f"{c}_component")), c, "left").withColumn(f"{c}_component", F.coalesce(f"{c}_component", c))
        many = members.filter("blocks > 1")
        leads = named(many.select("lead").distinct(), "lead")
        placed = keep(named(_by_lead(many, leads), "id"), "placed")
        strays = placed.filter("id_component <> lead_component")
        if strays.isEmpty():
            return None
        parts = strays.groupBy("lead").agg(F.ceil(F.count(F.lit(1)) / BLOCK).alias("parts"))
        stray = _by_lead(strays, parts).select("lead", "blocks", F.pmod(F.xxhash64("id", F.lit(5)), F.col("parts")).alias("part"), "id", F.col("block").alias("home"), F.col("id_component").alias("component"))
        every = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.col(n) - 1))
        there = _by_lead(placed, parts).select("lead", "block", every("parts").alias("part"), "id", F.col("id_component").alias("component"), F.lit(False).alias("pivot"))
        to = stray.withColumn("block", every("blocks")).filter("block <> home")
        rows = there.unionByName(to.select("lead", "block", "part", "id", "component", F.lit(True).alias("pivot"))).join(self.models.select("id", "n", "sketch"), "id")
        keys = ("lead", "block", "part")
        rows = rows.select(*keys, "id", "component", "pivot", "n", "sketch").repartition(*keys).sortWithinPartitions(*keys)
        pairs = keep(rows.mapInArrow(_guess(percent), "a long, b long").distinct(), "pairs")
        if pairs.isEmpty():
            return None
        ids = pairs.select(F.col("a").alias("id")).union(pairs.select(F.col("b").alias("id"))).distinct()
        texts = keep(self.texts(ids).mapInArrow(_matching, "id long, text string").dropDuplicates(["id"]), "pair texts")
        both = pairs.join(texts.select(F.col("id").alias("a"), F.col("text").alias("own")), "a").join(texts.select(F.col("id").alias("b"), F.col("text").alias("other")), "b")
        return keep(both.select("a", "b", "own", "other").mapInArrow(_verify(percent), "a long, b long"), "late links")

    def result(self) -> DataFrame:
        keep = self.scratch.keep
        star = keep(self.stars(), "stars")
        texts = keep(self.texts(star.select("id").union(star.select("lead")).distinct()), "texts")
        # Lead and members in blocks; the lead is in every block.
        weighed = star.join(self.models.select("id", "n"), "id").groupBy("lead").agg(F.count(F.lit(1)).alias("classes"), F.sum("n").alias("n"))
        blocks = keep(weighed.select("lead", F.greatest(F.ceil(F.col("classes") / BLOCK), F.ceil(F.col("n") / BLOCK_SHINGLES)).alias("blocks")), "blocks")
        large = blocks.filter("blocks > 1")
        several = not large.isEmpty()
        members = _by_lead(star, large, "left") if several else star.withColumn("blocks", F.lit(1).cast("long"))
        members = members.withColumn("blocks", F.coalesce("blocks", F.lit(1).cast("long"))).withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")))
        leads = blocks.select("lead", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("block"), F.col("lead").alias("id"))
        rows = members.select("lead", "block", "id").unionByName(leads).join(texts, "id").join(self.models.select("id", "sketch"), "id").select("lead", "block", "id", "text", "digest", "sketch")
        links = keep(rows.repartition("lead", "block").sortWithinPartitions("lead", "block").mapInArrow(_search(self.percent), "a long, b long"), "links")
        final = keep(components(links, self.scratch), "components")
        if several and (late := self.second_look(members, final)) is not None:
            final = components(links.union(late), self.scratch)
        part = self.classes.join(final, self.classes.id == final.node, "left").select("id", "digest", "least", F.coalesce("component", "id").alias("component"))
        named = part.groupBy("component").agg(F.min("least").alias("component_id"), F.count(F.lit(1)).alias("classes"))
        # A component of one class needs no look-up; the others are few, and their classes are dealt out.
        verdict = _by_lead(part, named.filter("classes > 1").drop("classes"), "left", "component").select("digest", F.coalesce("component_id", "least").alias("component_id"))
        out = self.sets.select("doc_id", F.col("n").alias("n_shingles"), "digest").join(verdict, "digest", "left")
        alone = (F.col("n_shingles") == 0) | F.col("doc_id").isNull()
        component = F.when(alone, F.col("doc_id")).otherwise(F.col("component_id"))
        return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def _by_lead(rows: DataFrame, per_lead: DataFrame, how: str = "inner", lead: str = "lead") -> DataFrame:
    """rows (lead, id) with what is known of their lead. The rows of a lead are dealt to SALTS places, each of which has
    a copy of that, so a lead of very many classes is not in one task."""
    copied = per_lead.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    return rows.withColumn("salt", F.pmod(F.xxhash64("id", F.lit(3)), F.lit(SALTS))).join(copied, [lead, "salt"], how).drop("salt")


def near_dedup(docs: DataFrame, *, percent: int = 75, scratch: Scratch | None = None) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row; documents are linked from ``percent`` similarity on.

    Texts are lower-cased in A-Z; a shingle is five words, or all words of a shorter text; texts of any length are compared
    whole. A null or blank text has no shingle, is linked with nothing and is kept. A null doc_id is linked with nothing,
    has no component and is kept. Rows of one doc_id with different texts are judged each by its own text. Of documents
    that tie, the smallest doc_id names the component. Other columns are not read, an empty table gives an empty result.
    """
    return NearDuplicates(docs, percent, scratch or Scratch(docs.sparkSession)).result()


def op2_near_dedup(spark, sf_dir: str) -> DataFrame:
    return near_dedup(spark.read.parquet(f"{sf_dir}/documents.parquet"))


OP2_SQL = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w
  FROM documents),
sets AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [w] ELSE list_distinct(list_transform(range(1, len(w) - 3), lambda i: w[i:i + 4])) END AS s FROM words),
sizes AS (SELECT doc_id, len(s) AS n FROM sets),
flat AS (SELECT doc_id, unnest(s) AS g FROM sets),
ids AS (SELECT doc_id, hash(g) AS h, g FROM flat),
met AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS common FROM ids a JOIN ids b ON a.h = b.h AND a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
links AS (SELECT a, b FROM met JOIN sizes x ON x.doc_id = a JOIN sizes y ON y.doc_id = b WHERE 100 * common >= 75 * (x.n + y.n - common)),
ways AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach AS (SELECT doc_id AS node, doc_id AS low FROM sizes UNION SELECT w.b, r.low FROM reach r JOIN ways w ON w.a = r.node AND r.low < w.b)
SELECT doc_id, CAST(n AS BIGINT) AS n_shingles, min(low) AS component_id, min(low) = doc_id AS kept FROM sizes JOIN reach ON node = doc_id GROUP BY doc_id, n
"""
