import random
import re
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from halograph.llm import exact_dedup, near_dedup, suffix_dedup
from halograph.llm.column_bwt import build

LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def exact_truth(pairs, keep):
    groups = defaultdict(list)
    for i, t in pairs:
        groups[(t or "").encode().translate(LOWER)].append(i)
    out = []
    for i, t in pairs:
        ids = groups[(t or "").encode().translate(LOWER)]
        real = [x for x in ids if x is not None]
        k = (min if keep == "smallest" else max)(real) if real else None
        out.append((i, k, len(ids), i is not None and i == k))
    return sorted(map(str, out))


@pytest.mark.parametrize("keep", ["smallest", "largest"])
@pytest.mark.parametrize("weak", [False, True])
def test_exact(make_docs, edge, keep, weak):
    """Also with a digest that maps different texts together, so byte verification has to split them."""
    digest = (lambda t: (F.char_length(t) % 3).cast("string")) if weak else exact_dedup.sha256_digest
    pairs = edge + [(100 + i, f"text {i % 5}") for i in range(40)] + [(None, "lonely"), (None, "Lonely")]
    got = exact_dedup.exact_dedup(make_docs(pairs, ["digest", "n"]), keep=keep, digest=digest)
    assert sorted(str((r.doc_id, r.keep_id, r.group_size, r.kept)) for r in got.collect()) == exact_truth(pairs, keep)


def test_exact_large_group_and_none(make_docs):
    got = exact_dedup.exact_dedup(make_docs([(i, "same") for i in range(1500)]), keep="largest")
    assert got.filter("keep_id = 1499 AND group_size = 1500").count() == 1500 and got.filter("kept").count() == 1
    assert exact_dedup.exact_dedup(make_docs([])).count() == 0


def shingles(t):
    w = re.findall(rb"[^\x20\x09-\x0d]+", (t or "").encode().translate(LOWER))
    return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])


def near_truth(pairs):
    sets = {i: shingles(t) for i, t in pairs}
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = list(sets)
    for a in range(len(ids)):
        for b in range(a):
            x, y = sets[ids[a]], sets[ids[b]]
            if x and y and 100 * len(x & y) >= 75 * len(x | y):
                p, q = root(ids[a]), root(ids[b])
                parent[max(p, q)] = min(p, q)
    return {i: (len(sets[i]), root(i)) for i in sets}


def variants(n, rate, seed=3, words=60):
    rng = random.Random(seed)
    base = [f"w{rng.randrange(5000)}" for _ in range(words)]
    out = []
    for _ in range(n):
        w = list(base)
        for _ in range(rng.randint(0, int(rate * words))):
            w[rng.randrange(words)] = f"z{rng.randrange(10**6)}"
        out.append(" ".join(w))
    return out


@pytest.mark.parametrize("block", [4, 1024])
def test_near(make_docs, monkeypatch, block):
    """Groups in which many are linked with the lead, some only with each other, and some with none."""
    monkeypatch.setattr(near_dedup, "BLOCK", block)
    texts = variants(60, 0.12) + variants(20, 0.05, 9) + ["a b c", "A  b\tC", "a b c d", "one", None, "", "   ", "dup text " * 30, "dup text " * 31]
    pairs = list(enumerate(texts, 10))
    got = {r.doc_id: r for r in near_dedup.near_dedup(make_docs(pairs, ["component", "sketch"])).collect()}
    for i, (n, c) in near_truth(pairs).items():
        assert (got[i].n_shingles, got[i].component_id, got[i].kept) == (n, c, i == c)


def test_near_edges(make_docs):
    got = near_dedup.near_dedup(make_docs([(5, "x y"), (5, "x y"), (None, "x y"), (2, "x y"), (9, None)])).collect()
    assert sorted(str((r.doc_id, r.component_id, r.kept)) for r in got) == sorted(map(str, [(5, 2, False), (5, 2, False), (None, None, True), (2, 2, True), (9, 9, True)]))
    assert near_dedup.near_dedup(make_docs([])).count() == 0


def test_near_repeated_identifiers(make_docs):
    """Texts that share a doc_id are classes of their own, each with its own links."""
    a, b = variants(2, 0.03, 5)[0], variants(2, 0.03, 6)[0]
    near = lambda t: t + " end"
    got = near_dedup.near_dedup(make_docs([(4, a), (4, b), (7, near(a)), (8, near(b)), (3, "far off")])).collect()
    assert sorted((r.doc_id, r.component_id, r.kept) for r in got) == [(3, 3, True), (4, 4, True), (4, 4, True), (7, 4, False), (8, 4, False)]


def test_near_a_bucket_of_unlinked_classes(make_docs, monkeypatch):
    """Classes that share a third of their shingles with each other, few of them linked: blocks pass sketches, not texts."""
    monkeypatch.setattr(near_dedup, "BLOCK", 16)
    rng = random.Random(12)
    common = " ".join(f"c{k}" for k in range(45))
    texts = [f"{common} " + " ".join(f"v{rng.randrange(10**6)}" for _ in range(22)) for _ in range(150)]
    texts += [t + " tail" for t in texts[100:120]]
    pairs = list(enumerate(texts))
    got = {r.doc_id: r.component_id for r in near_dedup.near_dedup(make_docs(pairs)).collect()}
    assert got == {i: c for i, (_, c) in near_truth(pairs).items()}


def test_likelihood_passes_pairs_at_the_threshold():
    """Recall of estimate and bands over pairs of similarity 0.75 to 0.8 and sets of many sizes."""
    rng, passed, met, total = np.random.default_rng(6), 0, 0, 0
    for size in (4, 8, 30, 100, 1000):
        for _ in range(40):
            share = int(np.ceil(1.5 * size / 1.75))
            u = rng.integers(0, 1 << 63, 2 * size - share, dtype=np.uint64)
            a, b = near_dedup.registers(u[:size]), near_dedup.registers(u[size - share :])
            passed += len(near_dedup._likely(a, size, b[None], np.array([size]), 75))
            met += bool((near_dedup.band_keys(a[None]) == near_dedup.band_keys(b[None])).any())
            total += 1
    assert passed == met == total


def test_registers_merge_and_estimate():
    rng = np.random.default_rng(1)
    u = rng.integers(0, 1 << 63, 3000, dtype=np.uint64)
    a, b = near_dedup.registers(u[:2000]), near_dedup.registers(u[1000:])
    assert (np.maximum(a, b) == near_dedup.registers(u)).all()
    guess = near_dedup.likeliest_similarity(a[None], b[None], np.array([2000.0]), np.array([2000.0]))[0]
    assert abs(guess - 1 / 3) < 0.1


def test_collection_transform():
    rng = random.Random(3)
    for trial in range(30):
        strings = [bytes(rng.choice(b"ab\x00" if trial % 2 else b"abcd") for _ in range(rng.randint(0, 12))) for _ in range(rng.randint(0, 9))]
        n = np.array([len(s) for s in strings], np.int64)
        start = (np.cumsum(n) - n).astype(np.int64)
        bwt, lcp, names = build(np.frombuffer(b"".join(strings), np.uint8), start, n, block=rng.choice([2, 5, 999]), in_memory=rng.choice([0, 10**6]))
        suffixes = [strings[x // 128][len(strings[x // 128]) - x % 128 :] for x in names.tolist()]
        assert suffixes == sorted(suffixes) and len(suffixes) == int((n + 1).sum())
        for i, s in enumerate(suffixes):
            k = 0
            while i and k < min(len(s), len(suffixes[i - 1])) and s[k] == suffixes[i - 1][k]:
                k += 1
            assert lcp[i] == k


def repeat_truth(pairs):
    seen = {}
    rows = [(i, (t or "").encode()) for i, t in pairs]
    for i, b in rows:
        if i is not None:
            for p in range(len(b) - 49):
                w = b[p : p + 50]
                seen[w] = min(seen.get(w, i), i)
    out = []
    for i, b in rows:
        gone = bytearray(len(b))
        for p in range(len(b) - 49):
            if i is not None and seen[b[p : p + 50]] < i:
                gone[p : p + 50] = b"\1" * 50
        spans = sum(1 for k in range(len(b)) if gone[k] and not (k and gone[k - 1]))
        out.append((i, len(b), sum(gone), spans, bytes(x for x, g in zip(b, gone) if not g)))
    return out


@pytest.mark.parametrize("heavy, in_memory", [(2, 0), (20_000, 0), (20_000, 8 << 20)])
def test_repeats(make_docs, sha, heavy, in_memory):
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdeé") for _ in range(rng.randint(2, 7)))
    text = lambda n: " ".join(word() for _ in range(n))
    passage, other = text(14), text(20)
    docs = [text(30) + passage + text(10), passage + other, other[3:] + text(5) + passage[5:70], passage[:49], passage[:50], "ab" * 300, "x" + "ab" * 100, None, "", passage + passage, text(60)]
    pairs = list(zip([7, 3, 12, 4, 5, 20, 21, 1, 2, 30, 9], docs)) + [(12, passage), (None, passage)]
    got = suffix_dedup.suffix_dedup(make_docs(pairs, ["chunk", "group"]), heavy=heavy, in_memory=in_memory).collect()
    assert sorted(str((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept), r.kept_sha256)) for r in got) == sorted(str((*x, sha(x[-1]))) for x in repeat_truth(pairs))
    for r in got:
        assert sum(s.stop - s.start for s in r.spans) == r.n_removed and len(r.spans) == r.n_spans


def test_repeats_of_nothing(make_docs):
    assert suffix_dedup.suffix_dedup(make_docs([])).count() == 0
    assert suffix_dedup.suffix_dedup(make_docs([(1, None)])).first().n_removed == 0


def test_repeats_far_into_a_long_text(make_docs):
    """Single windows that stand again beyond byte 2**24 of one text, and across the bounds of slices."""
    rng = random.Random(8)
    passages = [rng.randbytes(25).hex() for _ in range(40)]
    near, far = "".join(p + "-" for p in passages[:20]), "".join(p + "-" for p in passages[20:])
    long = near + rng.randbytes(1 << 23).hex() + "-" + far
    at = suffix_dedup.SLICE_BYTES - 25
    long = long[:at] + passages[0] + long[at + 50 :]
    got = suffix_dedup.suffix_dedup(make_docs([*enumerate(passages, 1), (99, long)]), texts=False).filter("doc_id = 99").first()
    assert len(far) + (1 << 24) < got.n_bytes and (got.n_removed, got.n_spans) == (41 * 50, 41)


def test_slices_hold_every_window_once(monkeypatch):
    rng = random.Random(2)
    texts = [bytes(rng.choice(b"abc") for _ in range(n)) for n in (0, 49, 50, 300, 64, 113, 114, 20, 1000)]
    ends = np.cumsum([len(t) for t in texts])
    chunk = object.__new__(suffix_dedup._Chunk)
    chunk.ids, chunk.known = np.arange(len(texts)), np.ones(len(texts), bool)
    chunk.offsets, chunk.data = np.concatenate([[0], ends]), np.frombuffer(b"".join(texts), np.uint8)

    def windows():
        return sorted((int(a) + k, int(d), int(h)) for a, n, d, h in zip(*chunk.runs()) for k in range(n))

    whole = windows()
    assert len(whole) == sum(max(0, len(t) - 49) for t in texts)
    monkeypatch.setattr(suffix_dedup, "SLICE_BYTES", 64)
    assert windows() == whole


def test_long_texts(make_docs, spark):
    """A text of some megabytes is compared, searched and cut whole, from end to end."""
    from halograph.llm import chat, decontaminate

    rng = random.Random(21)
    long = " ".join(f"w{rng.randrange(10**7)}" for _ in range(300_000))
    item = "the very last words of this text are those of a question"
    got = {r.doc_id: r for r in near_dedup.near_dedup(make_docs([(1, long), (2, long + " " + item), (3, item)])).collect()}
    assert (got[2].component_id, got[2].n_shingles, got[3].component_id) == (1, got[1].n_shingles + 12, 3)
    bench = spark.createDataFrame([(5, item)], "item_id long, text string")
    hit = decontaminate.contaminated(make_docs([(1, long), (2, long + " " + item)]), bench).collect()
    assert [(r.doc_id, r.item_id, r.distance, r.stop) for r in hit] == [(2, 5, 0, len(long) + 1 + len(item))]
    exact = exact_dedup.exact_dedup(make_docs([(1, long), (2, long.upper()), (3, long + "x")])).collect()
    assert sorted((r.doc_id, r.keep_id) for r in exact) == [(1, 1), (2, 1), (3, 3)]
    talk = chat.format_chat(spark.createDataFrame([(1, 0, "user", long, "x"), (1, 1, "user", "> " + long + "\nyes", "x")], "conv_id long, turn long, role string, text string, head string")).collect()
    assert sorted((r.turn, r.quotes, len(r.content)) for r in talk) == [(0, False, len(long)), (1, True, 3)]


def test_memtables_tiers_and_lookups(make_docs, spark):
    """Runs of few rows and a fan-in of two give several tiers, with the same verdicts."""
    from halograph.graph.scratch import Scratch

    pairs = [(i, f"text {i % 37}") for i in range(400)]
    got = exact_dedup.exact_dedup(make_docs(pairs), keep="largest", memtable_rows=16, fan_in=2)
    assert sorted(str((r.doc_id, r.keep_id, r.group_size, r.kept)) for r in got.collect()) == exact_truth(pairs, "largest")
    keyed, runs, level = exact_dedup.build_index(make_docs(pairs), Scratch(spark), memtable_rows=16, fan_in=2)
    assert runs.groupBy("run", "digest").count().filter("count > 1").isEmpty() and runs.select("run").distinct().count() >= 25
    digest = keyed.filter("doc_id = 5").first().digest
    found = exact_dedup.seen(level, [digest, "absent"]).collect()
    assert [(r.least, r.most, r.n) for r in found] == [(5, 375, 11)]
    assert "PushedFilters: [In(digest" in exact_dedup.seen(level, [digest, "absent"])._jdf.queryExecution().executedPlan().toString()


def test_texts_that_no_class_asks_for_are_not_moved(spark):
    docs = spark.range(3000).selectExpr("CASE WHEN id = 7 THEN NULL ELSE id END AS doc_id", "concat('text ', id) AS text")
    search = near_dedup.NearDuplicates(docs, 75, near_dedup.Scratch(spark))
    found = search.among(spark.range(20, 30).withColumnRenamed("id", "doc_id")).collect()
    assert {(i, f"text {i}") for i in range(20, 30)} <= {(r.doc_id, r.text) for r in found} and len(found) < 30
