"""The registered queries over a whole table against libraries and plain brute force, row by row."""

import base64
import hashlib
import math
import re

import numpy as np
import public_tokenizers as P
import pyarrow as pa
import pytest
from oracle import check
from test_scores import distance

from halograph.llm import decontaminate, queries, quality, toxicity
from halograph.llm.common import text_bytes

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def documents(spark):
    return {r.doc_id: r.text or "" for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}


@pytest.mark.parametrize("name", sorted(queries.ORACLE_SQL))
def test_sql(spark, name):
    check(spark, SF, queries.QUERIES[name], queries.ORACLE_SQL[name])


def test_token_counts(spark, documents):
    from tokenizers import Tokenizer

    own = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    got = {r.doc_id: r for r in queries.QUERIES["op1_token_counts"](spark, SF).collect()}
    assert got.keys() == documents.keys()
    for i, t in documents.items():
        n = len(own.encode(t, add_special_tokens=False).ids)
        assert (got[i].n_bytes, got[i].n_tokens, got[i].over_limit) == (len(t.encode()), n, n > 512)


def test_round_trip(spark, documents):
    import tiktoken

    with open(P.path("byte_bpe_multi_50k.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    own = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = {r.doc_id: r for r in queries.QUERIES["op5_bpe_roundtrip"](spark, SF).collect()}
    for i, t in documents.items():
        ids = own.encode_ordinary(t)
        sha = lambda b: hashlib.sha256(b).hexdigest()
        assert (got[i].n_tokens, got[i].ids_sha256, got[i].decoded_sha256) == (len(ids), sha(",".join(map(str, ids)).encode()), sha(t.encode()))


def test_benchmark_items(spark, documents):
    items = [(r.item_id, decontaminate.normalise(r.text or "")) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    want = {}
    for d, t in documents.items():
        n = decontaminate.normalise(t)
        for i, a in items:
            # the matrix is slow; an item within budget shares at least one of its pieces
            if a and any(p in n for _, p in decontaminate.pieces(a)) and (k := distance(a, n)) <= int(len(a) * decontaminate.RATE):
                want[d, i] = k
    assert {(r.doc_id, r.item_id): r.distance for r in queries.QUERIES["op10_decontaminate"](spark, SF).collect()} == want


def test_quality_scores(spark, documents):
    """Line by line: features of a text alone, sums over both labels of a line, lengths as weights."""
    model = quality.train(spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet"))
    got = {r.doc_id: r.score for r in queries.QUERIES["op6_quality_crf"](spark, SF).collect()}
    assert got.keys() == documents.keys()
    t = model["t"]
    for i, text in documents.items():
        x, size, _ = quality.line_features(*text_bytes(pa.array([text], pa.large_string())))
        e = x.astype(float) @ model["w"]
        assert len(e) == text.count("\n") + 1 and [int(s) for s in size] == [len(line) for line in text.encode().split(b"\n")]
        ahead, behind = [(0.0, e[0])], [(0.0, 0.0)]
        both = lambda a, b: max(a, b) + math.log1p(math.exp(-abs(a - b)))
        for v in e[1:]:
            a = ahead[-1]
            ahead.append((both(a[0] + t[0, 0], a[1] + t[1, 0]), v + both(a[0] + t[0, 1], a[1] + t[1, 1])))
        for v in e[:0:-1]:
            b = (behind[-1][0], behind[-1][1] + v)
            behind.append((both(t[0, 0] + b[0], t[0, 1] + b[1]), both(t[1, 0] + b[0], t[1, 1] + b[1])))
        good = [1 / (1 + math.exp(min(700, f[0] + b[0] - f[1] - b[1]))) for f, b in zip(ahead, behind[::-1])]
        m = min(max(float(np.average(good, weights=size + 1)), 1e-6), 1 - 1e-6)
        want = 1 / (1 + math.exp(-(math.log(m / (1 - m)) * model["curve"][0] + model["curve"][1])))
        assert abs(got[i] - want) < 1e-6


def test_severity(spark, documents):
    """Words by a pattern, weights summed over distinct ones, thresholds one by one."""
    model = toxicity.train(spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet"))
    got = {r.doc_id: r for r in queries.QUERIES["op4_toxicity"](spark, SF).collect()}
    weight = dict(zip(model["words"].tolist(), model["w"].tolist()))
    for i, text in documents.items():
        words = {w.lower() for w in re.findall(rb"[A-Za-z\x80-\xff]+", text.encode())}
        z = sum(weight.get(int(toxicity.document_words(*text_bytes(pa.array([w.decode("utf-8")], pa.large_string())))[1][0]), 0.0) for w in words)
        above = [1 / (1 + math.exp(c - z)) for c in model["cuts"]]
        assert abs(got[i].severity - sum(above)) < 1e-6 and got[i].toxic == (above[0] >= 0.5)
