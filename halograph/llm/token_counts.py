"""Token counts without token ids: pieces are counted once for each distinct pre-token.

Documents are packed into chunks of bounded text. A chunk carries its distinct pre-tokens and, for every document,
the frequencies as positions in that list, packed. The pre-tokens of all chunks meet by their text, each is counted once,
its count goes back to every chunk that has it, and a document's count is the weighted sum of its frequencies.
"""

from __future__ import annotations

import json
from collections import Counter

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halograph.llm.common import Scratch, worker_store

#: The split that byte-level pre-tokenizers apply (a fixed, public pattern).
SPLIT = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
CHUNK_BYTES = 16 << 20
#: Counted words that a worker keeps at once, and counts that it holds before they are packed and sent on.
KNOWN_WORDS, HELD_COUNTS = 300_000, 1 << 20
_CHUNK = "chunk long, vocab array<string>, ids array<long>, n_bytes array<long>, special array<int>, sizes array<int>, freq binary, pos binary"


def _chunks(pattern: str, special: list[str], most: int):
    def run(batches):
        from pyspark import TaskContext

        find = regex.compile(pattern).findall
        cut = regex.compile("|".join(map(regex.escape, sorted(special, key=len, reverse=True)))) if special else None
        chunk = TaskContext.get().partitionId() << 32

        def fresh():
            return {}, [], [], [], [], []

        vocab, ids, sizes, extra, pos, freq = fresh()
        held = 0

        def out():
            lists = ([list(vocab)], [ids], [sizes], [extra], [[len(p) for p in pos]])
            kinds = (pa.string(), pa.int64(), pa.int64(), pa.int32(), pa.int32())
            packed = [pa.array([_pack(x)], pa.binary()) for x in (freq, pos)]
            return pa.RecordBatch.from_arrays([pa.array([chunk], pa.int64()), *(pa.array(x, pa.list_(k)) for x, k in zip(lists, kinds)), *packed], names=["chunk", "vocab", "ids", "n_bytes", "special", "sizes", "freq", "pos"])

        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                text = text.as_py() or ""
                n = len(text.encode())
                if held and held + n > most:
                    yield out()
                    chunk += 1
                    held = 0
                    vocab, ids, sizes, extra, pos, freq = fresh()
                held += n
                found = 0
                if cut is not None and any(s in text for s in special):
                    parts = cut.split(text)
                    found = len(parts) - 1
                    counts = Counter()
                    for part in parts:
                        counts.update(find(part))
                else:
                    counts = Counter(find(text))
                new = vocab.setdefault
                at = np.fromiter([new(t, len(vocab)) for t in counts], np.int32, len(counts))
                order = at.argsort()
                at = at[order]
                pos.append(np.diff(at, prepend=np.int32(0)))  # steps between rising positions pack well
                freq.append(np.fromiter(counts.values(), np.int32, len(counts))[order])
                ids.append(doc)
                sizes.append(n)
                extra.append(found)
        if ids:
            yield out()

    return run


def _pack(parts: list[np.ndarray]) -> bytes:
    """Numbers as four planes of bytes, compressed; the high planes are almost all zero."""
    flat = np.concatenate(parts) if parts else np.zeros(0, np.int32)
    raw = flat.astype("<i4").view(np.uint8).reshape(-1, 4).T.tobytes()
    return len(flat).to_bytes(8, "little") + pa.compress(raw, "zstd", asbytes=True)


def _unpack(packed: bytes) -> np.ndarray:
    n = int.from_bytes(packed[:8], "little")
    raw = pa.decompress(packed[8:], 4 * n, "zstd", asbytes=True) if n else b""
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(4, n).T).view("<i4").ravel()


def _count_pieces(tokenizer_json: str):
    def run(batches):
        from tokenizers import Tokenizer

        store = worker_store("tokenizer")
        key = hash(tokenizer_json)
        if key not in store:
            store[key] = Tokenizer.from_str(tokenizer_json)
            store[key].encode_special_tokens = True
        encode, known = store[key].encode_batch, {}
        held, n = [], 0
        for batch in batches:  # all rows of a pre-token come to one task
            words = batch.column(0).dictionary_encode()
            distinct = words.dictionary.to_pylist()
            if len(known) > KNOWN_WORDS:
                known = {}
            new = [w for w in distinct if w not in known]
            for i in range(0, len(new), 2000):
                known.update(zip(new[i : i + 2000], [len(e.ids) for e in encode(new[i : i + 2000], add_special_tokens=False)]))
            each = np.array([known[w] for w in distinct], np.int32)
            held.append((batch.column(1).to_numpy(), batch.column(2).to_numpy(), each[words.indices.to_numpy()]))
            n += batch.num_rows
            if n >= HELD_COUNTS:
                yield _by_chunk(held)
                held, n = [], 0
        if held:
            yield _by_chunk(held)

    return run


def _by_chunk(held: list[tuple]) -> pa.RecordBatch:
    """chunk and, packed, the places in its list of pre-tokens, as steps, and the pieces of each."""
    chunk, at, pieces = (np.concatenate(x) for x in zip(*held))
    order = np.lexsort((at, chunk))
    chunk, at, pieces = chunk[order], at[order], pieces[order]
    own, first = np.unique(chunk, return_index=True)
    cuts = list(zip(first.tolist(), [*first[1:].tolist(), len(chunk)]))
    packed = [[_pack([np.diff(at[a:b], prepend=np.int32(0))]) for a, b in cuts], [_pack([pieces[a:b]]) for a, b in cuts]]
    return pa.RecordBatch.from_arrays([pa.array(own, pa.int64()), *(pa.array(x, pa.binary()) for x in packed)], names=["chunk", "at", "pieces"])


def _sum(batches):
    for batch in batches:
        cols = dict(zip(batch.schema.names, batch.columns))
        ids, sizes, totals = [], [], []
        for i in range(batch.num_rows):
            counts = [(np.cumsum(_unpack(c["at"]), dtype=np.int64), _unpack(c["pieces"])) for c in cols["counts"][i].as_py() or ()]
            pieces = np.zeros(sum(len(a) for a, _ in counts), np.int64)
            for a, n in counts:
                pieces[a] = n
            each = np.array(cols["sizes"][i].as_py(), np.int64)
            ends = np.cumsum(each)
            steps, freq = _unpack(cols["pos"][i].as_py()).astype(np.int64), _unpack(cols["freq"][i].as_py())
            at = np.cumsum(steps)
            begins = (ends - each)[each > 0]
            base = np.zeros(len(each), np.int64)
            base[each > 0] = at[begins] - steps[begins]
            weighted = np.zeros(len(at) + 1, np.int64)
            np.cumsum(pieces[at - np.repeat(base, each)] * freq, out=weighted[1:])
            totals.append(weighted[ends] - weighted[ends - each] + np.array(cols["special"][i].as_py(), np.int64))
            ids += cols["ids"][i].as_py()
            sizes += cols["n_bytes"][i].as_py()
        totals = np.concatenate(totals) if totals else np.zeros(0, np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(sizes, pa.int64()), pa.array(totals)], names=["doc_id", "n_bytes", "n_tokens"])


def token_counts(docs: DataFrame, tokenizer_json: str, *, limit: int = 512, chunk_bytes: int = CHUNK_BYTES, scratch: Scratch | None = None) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row, as a byte-level tokenizer of the given definition counts.

    No begin, end or added tokens; a special string inside a text counts as its one token. A null text is empty (0
    tokens). Repeated rows give repeated rows, a null doc_id stays null, other columns are ignored, an empty table gives
    an empty result. A text longer than ``chunk_bytes`` makes a chunk of its own.
    """
    scratch = scratch or Scratch(docs.sparkSession)
    special = [t["content"] for t in json.loads(tokenizer_json)["added_tokens"]]
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    chunks = scratch.keep(source.mapInArrow(_chunks(SPLIT, special, chunk_bytes), _CHUNK), "chunks")
    vocab = chunks.select("chunk", F.posexplode("vocab").alias("at", "token"))
    counted = vocab.select("token", "chunk", "at").repartition("token").mapInArrow(_count_pieces(tokenizer_json), "chunk long, at binary, pieces binary")
    counts = counted.groupBy("chunk").agg(F.collect_list(F.struct("at", "pieces")).alias("counts"))  # at most the pre-tokens of a chunk
    # A chunk whose documents are all empty has no pre-token.
    whole = chunks.drop("vocab").join(counts, "chunk", "left").drop("chunk")
    summed = whole.mapInArrow(_sum, "doc_id long, n_bytes long, n_tokens long")
    return summed.withColumn("over_limit", F.col("n_tokens") > limit)


def op1_token_counts(spark, sf_dir: str, tokenizer: str | None = None) -> DataFrame:
    import public_tokenizers

    with open(tokenizer or public_tokenizers.path("byte_bpe_50k.json"), encoding="utf-8") as f:
        definition = f.read()
    return token_counts(spark.read.parquet(f"{sf_dir}/documents.parquet"), definition)
