"""Byte-level BPE by a segment tree over byte positions.

A leaf holds the rank of the pair that starts at its byte, an inner node the leftmost smallest rank below it. A merge
reads the root, joins two live neighbours and updates the at most three leaves whose pairs changed, so a pre-token of n
bytes takes O(n log n) whatever its length.
"""

from __future__ import annotations

import base64
import hashlib

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halograph.llm.common import worker_store
from halograph.llm.token_counts import SPLIT

NONE = 1 << 60
#: Encodings of a generation; a worker keeps two, and what the older one holds is taken over when it is asked for.
CACHE_ENTRIES = 300_000


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def merge_pieces(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of one pre-token: always the leftmost pair of the lowest rank is joined next."""
    if piece in ranks:
        return [ranks[piece]]
    n = len(piece)
    size = 1
    while size < n:
        size *= 2
    # key = rank * size + position: the smallest key is the leftmost of the lowest rank
    tree = [NONE] * (2 * size)
    get = ranks.get
    for i in range(n - 1):
        r = get(piece[i : i + 2])
        if r is not None:
            tree[size + i] = r * size + i
    for v in range(size - 1, 0, -1):
        a, b = tree[2 * v], tree[2 * v + 1]
        tree[v] = a if a < b else b
    end = list(range(1, n + 1))  # where the live piece that starts here ends
    before = list(range(-1, n - 1))
    low = size - 1
    while (key := tree[1]) < NONE:
        i = key & low
        j = end[i]
        k = end[i] = end[j]
        changed = [(j, NONE)]
        if k < n:
            before[k] = i
            r = get(piece[i : end[k]])
            changed.append((i, NONE if r is None else r * size + i))
        else:
            changed.append((i, NONE))
        if (h := before[i]) >= 0:
            r = get(piece[h:k])
            changed.append((h, NONE if r is None else r * size + h))
        for v, key in changed:
            v += size
            tree[v] = key
            v >>= 1
            while v:
                a, b = tree[2 * v], tree[2 * v + 1]
                least = a if a < b else b
                if tree[v] == least:
                    break
                tree[v] = least
                v >>= 1
    ids, i = [], 0
    while i < n:
        ids.append(ranks[piece[i : end[i]]])
        i = end[i]
    return ids


class _Known(dict):
    """Encodings by pre-token; one that is not there yet is made by ``fill``."""

    def __init__(self, fill):
        super().__init__()
        self.fill = fill

    def __missing__(self, word: str):
        self.fill(word)
        return dict.__getitem__(self, word)


class ByteBpe:
    """Encoder and decoder over a rank table. ``encode`` gives ids, ``decode`` the bytes again."""

    def __init__(self, ranks: dict[bytes, int], pattern: str = SPLIT):
        self.ranks, self.find = ranks, regex.compile(pattern).findall
        self.bytes_of = {i: b for b, i in ranks.items()}
        self.ids_text, self.back = _Known(self._fill), _Known(self._fill)
        self.older: tuple[dict, dict] = ({}, {})

    def _fill(self, word: str) -> None:
        """The word's ids as text, and the bytes that these ids decode to."""
        if len(self.ids_text) >= CACHE_ENTRIES:
            self.older = (dict(self.ids_text), dict(self.back))
            self.ids_text.clear()
            self.back.clear()
        if word in self.older[0]:
            self.ids_text[word], self.back[word] = self.older[0][word], self.older[1][word]
            return
        ids = merge_pieces(word.encode(), self.ranks)
        self.ids_text[word] = ",".join(map(str, ids))
        self.back[word] = self.decode(ids)

    def encode(self, text: str) -> list[int]:
        return [i for w in self.find(text) for i in merge_pieces(w.encode(), self.ranks)]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))

    def digest(self, text: str) -> tuple[int, str, str]:
        """Number of ids, SHA-256 of the ids joined by commas, SHA-256 of the decoded bytes."""
        words = self.find(text)
        ids = ",".join(map(self.ids_text.__getitem__, words))
        back = b"".join(map(self.back.__getitem__, words))
        return ids.count(",") + 1 if words else 0, hashlib.sha256(ids.encode()).hexdigest(), hashlib.sha256(back).hexdigest()


def _codec(shared) -> ByteBpe:
    store = worker_store("bpe")
    if shared.id not in store:
        if len(store) >= 4:
            store.clear()
        store[shared.id] = ByteBpe(*shared.value)
    return store[shared.id]


class _Shared:
    """A broadcast rank table (a vocabulary file, of fixed size), named by its content and the pattern in the workers."""

    def __init__(self, spark, path: str, pattern: str):
        ranks = read_ranks(path)
        content = hashlib.sha256(b"".join(b + i.to_bytes(8, "little") for b, i in ranks.items()) + pattern.encode())
        self.held, self.id = spark.sparkContext.broadcast((ranks, pattern)), content.hexdigest()

    @property
    def value(self):
        return self.held.value


def bpe_digests(docs: DataFrame, ranks_path: str, pattern: str = SPLIT) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every row: ids and round trip without a stored id list.

    A null text is empty (no id; the hashes of nothing). Repeated rows give repeated rows, a null doc_id stays null, other
    columns are ignored, an empty table gives an empty result; texts of any length are encoded whole.
    """
    shared = _Shared(docs.sparkSession, ranks_path, pattern)

    def run(batches):
        codec = _codec(shared)
        for batch in batches:
            rows = [codec.digest(t.as_py() or "") for t in batch.column(1)]
            n, ids, back = zip(*rows) if rows else ((), (), ())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(back, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def bpe_encode(docs: DataFrame, ranks_path: str, pattern: str = SPLIT) -> DataFrame:
    """Adds token_ids array<int> to every row; a null text has no ids. A column of that name is replaced."""
    shared = _Shared(docs.sparkSession, ranks_path, pattern)

    @F.pandas_udf("array<int>")
    def encode(texts):
        codec = _codec(shared)
        return texts.map(lambda t: codec.encode(t or ""), na_action=None)

    return docs.withColumn("token_ids", encode(F.col("text")))


def bpe_decode(encoded: DataFrame, ranks_path: str, pattern: str = SPLIT) -> DataFrame:
    """Adds decoded binary from token_ids; a null list has no bytes."""
    shared = _Shared(encoded.sparkSession, ranks_path, pattern)

    @F.pandas_udf("binary")
    def decode(ids):
        codec = _codec(shared)
        return ids.map(lambda x: codec.decode([int(i) for i in x]) if x is not None else b"", na_action=None)

    return encoded.withColumn("decoded", decode(F.col("token_ids")))


def op5_bpe_roundtrip(spark, sf_dir: str, ranks: str | None = None) -> DataFrame:
    import public_tokenizers

    return bpe_digests(spark.read.parquet(f"{sf_dir}/documents.parquet"), ranks or public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
