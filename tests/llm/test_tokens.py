import base64
import random

import public_tokenizers as P
import pytest

from halograph.llm import bpe, token_counts

JSON = P.path("byte_bpe_50k.json")
RANKS = P.path("byte_bpe_multi_50k.tiktoken")


@pytest.fixture(scope="module")
def reference():
    import tiktoken

    with open(RANKS, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


@pytest.mark.parametrize("chunk", [64, 1 << 20])
def test_counts(make_docs, edge, chunk):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(JSON)
    got = token_counts.token_counts(make_docs(edge, ["tokens", "chunk", "vocab"]), open(JSON).read(), chunk_bytes=chunk).collect()
    want = [(i, len((x or "").encode()), len(t.encode(x or "", add_special_tokens=False).ids)) for i, x in edge]
    key = lambda r: (r[0] is None, r[0] or 0, r[1], r[2])
    assert sorted([(r.doc_id, r.n_bytes, r.n_tokens) for r in got], key=key) == sorted(want, key=key)
    assert all(r.over_limit == (r.n_tokens > 512) for r in got)


def test_counts_of_nothing(make_docs):
    assert token_counts.token_counts(make_docs([]), open(JSON).read()).count() == 0
    assert token_counts.token_counts(make_docs([(1, None), (2, "")]), open(JSON).read()).count() == 2


def test_bpe(make_docs, edge, reference, sha):
    got = bpe.bpe_digests(make_docs(edge), RANKS).collect()
    want = []
    for i, x in edge:
        ids = reference.encode_ordinary(x or "")
        want.append((i, len(ids), sha(",".join(map(str, ids)).encode()), sha((x or "").encode())))
    assert sorted(map(str, [tuple(r) for r in got])) == sorted(map(str, want))
    assert bpe.bpe_digests(make_docs([]), RANKS).count() == 0


def test_bpe_columns(make_docs, edge, reference):
    enc = bpe.bpe_encode(make_docs(edge), RANKS)
    for r in bpe.bpe_decode(enc, RANKS).collect():
        assert list(r.token_ids) == reference.encode_ordinary(r.text or "") and bytes(r.decoded) == (r.text or "").encode()


def test_merges_by_segment_tree(reference):
    random.seed(5)
    ranks = bpe.read_ranks(RANKS)
    for n in (1, 2, 3, 5, 17, 64, 300):
        for alphabet in ("ab", "theran ", "é日🙂x"):
            piece = "".join(random.choice(alphabet) for _ in range(n)).encode()
            assert bpe.merge_pieces(piece, ranks) == reference._encode_single_piece(piece)


def test_one_vocabulary_with_two_patterns(spark, make_docs, tmp_path):
    """A worker keeps codecs by what they hold, not by the name of the file."""
    import base64

    path = tmp_path / "ranks"
    pieces = [bytes([b]) for b in range(256)] + [b"ab", b"abab"]
    path.write_text("".join(f"{base64.b64encode(p).decode()} {i}\n" for i, p in enumerate(pieces)))
    docs = make_docs([(1, "abab ab")])
    count = lambda pattern: bpe.bpe_digests(docs, str(path), pattern).collect()[0].n_tokens
    assert (count(r"\S+|\s"), count(r"\S\S|\s")) == (3, 4)
    path.write_text("".join(f"{base64.b64encode(p).decode()} {i}\n" for i, p in enumerate(pieces[:256])))
    assert count(r"\S+|\s") == 7
