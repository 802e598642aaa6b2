import zlib

import numpy as np

from halograph.llm import decontaminate, quality, toxicity
from halograph.llm.common import text_bytes

SF = "/root/testdata/sf0.01"


def out_of(doc_id):
    return zlib.crc32(str(doc_id).encode()) % 4 == 2


def test_quality_on_held_out(spark):
    got = {r.doc_id: r for r in quality.op6_quality_crf(spark, SF).collect()}
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    held = [i for i in labels if out_of(i)]
    assert all(got[i].held_out == out_of(i) for i in got)
    assert np.mean([got[i].predicted == labels[i] for i in held]) > 0.9
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in got.values())


def test_quality_edges(spark, make_docs, edge):
    model = quality.fit(["Clean words in a line here.\nAnd more of them.", "### $$$ ### a$$$ b%%%\nx### y&&&"] * 20, [1, 0] * 20)
    docs = make_docs(edge + [(50, "\n\n\n"), (51, "good line of text\n" * 3000)], ["score"])
    assert quality.score_documents(docs, model).count() == len(edge) + 2
    kept = quality.keep_good(docs, model, 0.0)
    assert kept.columns == docs.columns and kept.count() == docs.count()
    assert quality.score_documents(make_docs([]), model).count() == 0
    assert quality.fit([], [])["constant"] == 0.5 and quality.fit(["a"], [1])["constant"] == 1.0
    lines = dict(quality.line_marginals(model, "Clean words in a line.\n### $$$ %%% a### &&&"))
    assert lines["Clean words in a line."] > lines["### $$$ %%% a### &&&"]


def test_chain_marginals_against_all_labellings():
    rng = np.random.default_rng(2)
    e, t = rng.normal(size=6), rng.normal(size=(2, 2))
    first = np.array([0, 4, 6])
    forward, backward = quality.Chain(first).messages(e, t)
    for a, b in zip(first, first[1:]):
        weight, good = 0.0, np.zeros(b - a)
        for k in range(2 ** (b - a)):
            y = [(k >> i) & 1 for i in range(b - a)]
            w = np.exp(sum(e[a + i] * y[i] for i in range(b - a)) + sum(t[y[i], y[i + 1]] for i in range(b - a - 1)))
            weight += w
            good += w * np.array(y)
        assert np.allclose(good / weight, 1 / (1 + np.exp(-(forward + backward)[a:b])))


def test_texts_of_many_lines_in_segments(make_docs):
    rng = np.random.default_rng(4)
    t, w = rng.normal(size=(2, 2)), rng.normal(size=quality.N_FEATURES) / 3
    for n in (1, 2, 3, 50, 700):
        text = "\n".join("".join(rng.choice(list("abc ABC#$ 12.|"), rng.integers(0, 30)).tolist()) for _ in range(n))
        data, offsets = text_bytes(__import__("pyarrow").array([text], "large_string"))
        x, size, first = quality.line_features(data, offsets)
        want = quality._mean_marginal(x, size, first, w, t)[0]
        for most in (1, 2, 5, 64, 1000):
            assert abs(quality.long_marginal(data, w, t, most) - want) < 1e-9
    model = quality.fit(["Clean words in a line here.\nAnd more of them.", "### $$$ ### a$$$ b%%%\nx### y&&&"] * 20, [1, 0] * 20)
    got = {r.doc_id: r.score for r in quality.score_documents(make_docs([(1, "\n" * 300_000), (2, "a line of words\n" * 60_000), (3, None)]), model).collect()}
    assert len(got) == 3 and all(0 <= v <= 1 for v in got.values())


def test_toxicity(spark):
    got = {r.doc_id: r for r in toxicity.op4_toxicity(spark, "/root/testdata/sf0.1").collect()}
    labels = {r.doc_id: r.toxic for r in spark.read.parquet("/root/testdata/sf0.1/labels.parquet").collect()}
    held = [i for i in labels if out_of(i)]
    caught = [got[i].toxic for i in held if labels[i]]
    wrong = [got[i].toxic for i in held if not labels[i]]
    assert np.mean(caught) > 0.85 and np.mean(wrong) < 0.02
    assert all(0 <= r.severity <= 3 for r in got.values())


def test_toxicity_edges(make_docs, edge):
    rows = [(np.array([1 << 60, 2 << 60], np.uint64), 1), (np.array([3 << 60], np.uint64), 0)] * 20
    model = toxicity.fit(rows)
    assert (np.diff(model["cuts"]) > 0).all()
    docs = make_docs(edge, ["severity"])
    assert toxicity.severity(docs, model).count() == len(edge)
    assert toxicity.severity(make_docs([]), model).count() == 0
    assert toxicity.severity(docs, toxicity.fit([])).filter("toxic").count() == 0


def test_severity_rises_with_telling_words():
    words = [f"bad{k}" for k in "abc"]
    texts = [" ".join(words[: 1 + i % 3]) + " plain text" for i in range(60)] + ["plain text"] * 60
    import pyarrow as pa

    doc, h = toxicity.document_words(*text_bytes(pa.array(texts, pa.large_string())))
    cut = np.searchsorted(doc, np.arange(len(texts) + 1))
    model = toxicity.fit([(np.unique(h[a:b]), int(i < 60)) for i, (a, b) in enumerate(zip(cut, cut[1:]))])
    grade, p = toxicity.Scorer(model).score(*text_bytes(pa.array(["plain text", "BADA plain", "bada badb badc"], pa.large_string())))
    assert grade[0] < 0.5 < grade[1] < grade[2] and p[0] < 0.5 < p[2]


def test_ordinal_likelihood_and_slopes():
    """Against the product of grade probabilities written out, and differences of it."""
    rng = np.random.default_rng(7)
    z, cuts, grade, weight = rng.normal(size=12), np.array([-0.5, 0.4, 1.7]), rng.integers(0, 4, 12), rng.random(12)
    above = lambda z, c: 1 / (1 + np.exp(-(z - c)))

    def direct(z, cuts):
        out = 0.0
        for v, g, u in zip(z, grade, weight):
            p = [1 - above(v, cuts[0]), above(v, cuts[0]) - above(v, cuts[1]), above(v, cuts[1]) - above(v, cuts[2]), above(v, cuts[2])][g]
            out -= u * np.log(p)
        return out

    loss, g_z, g_cut = toxicity.likelihood(z, cuts, grade, weight)
    assert abs(loss - direct(z, cuts)) < 1e-9
    for k in range(12):
        e = np.eye(12)[k] * 1e-6
        assert abs((direct(z + e, cuts) - direct(z - e, cuts)) / 2e-6 - g_z[k]) < 1e-5
    for k in range(3):
        e = np.eye(3)[k] * 1e-6
        assert abs((direct(z, cuts + e) - direct(z, cuts - e)) / 2e-6 - g_cut[k]) < 1e-5


def distance(pattern, text):
    """Least edit distance of the pattern to any part of the text, by the whole matrix."""
    row = [0] * (len(text) + 1)
    for i, a in enumerate(pattern, 1):
        new = [i]
        for j, b in enumerate(text, 1):
            new.append(min(new[-1] + 1, row[j] + 1, row[j - 1] + (a != b)))
        row = new
    return min(row)


def test_bit_parallel_distance():
    rng = np.random.default_rng(3)
    for _ in range(60):
        p = bytes(rng.choice(list(b"abc"), rng.integers(1, 90)).tolist())
        t = bytes(rng.choice(list(b"abc"), rng.integers(1, 150)).tolist())
        got = decontaminate.best_match(decontaminate.masks(p), len(p), t, len(p))
        assert got[0] == distance(p, t)


def test_matches_against_brute_force(spark, make_docs):
    rng = np.random.default_rng(5)
    word = lambda: "".join(rng.choice(list("abcdefgh"), rng.integers(2, 9)).tolist())
    text = lambda n: " ".join(word() for _ in range(n))
    items = [(k, text(12 + 5 * k)) for k in range(8)] + [(90, None), (91, "   "), (92, "Tiny"), (93, "quite short item")]
    docs = []
    for k, (i, t) in enumerate(items[:8]):
        for edits in range(0, 12, 2):
            s = list(t)
            for _ in range(edits):
                s[rng.integers(len(s))] = "Z"
            docs.append((len(docs), text(20) + "\n" + "".join(s).upper() + "  " + text(20)))
    docs += [(900, "a TINY  thing"), (901, None), (902, ""), (903, text(300)), (None, "tiny"), (905, "quite  short\nitem"), (906, "quite shorx item")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    want = set()
    for d, t in docs:
        for i, p in items:
            a, b = decontaminate.normalise(p or ""), decontaminate.normalise(t or "")
            if a and distance(a, b) <= int(len(a) * decontaminate.RATE):
                want.add((d, i))
    got = decontaminate.contaminated(make_docs(docs, ["item_id"]), bench).collect()
    assert {(r.doc_id, r.item_id) for r in got} == want
    blocks = decontaminate.contaminated(make_docs(docs), bench, block_bytes=200)
    assert {(r.doc_id, r.item_id) for r in blocks.collect()} == want
    by_id = dict(docs)
    for r in got:
        part = by_id[r.doc_id].encode()[r.start : r.stop]
        item = decontaminate.normalise(dict(items)[r.item_id])
        assert distance(item, decontaminate.normalise(part.decode())) == r.distance


def test_decontaminate_keeps_the_rest(spark, make_docs):
    bench = spark.createDataFrame([(1, "the quick brown fox jumps over the lazy dog")], "item_id long, text string")
    docs = make_docs([(1, "x The quick brown fox jumps over the lazy dog"), (2, "clean"), (None, "clean too"), (3, None)])
    assert sorted(str(r.doc_id) for r in decontaminate.decontaminate(docs, bench).collect()) == ["2", "3", "None"]
    assert decontaminate.contaminated(make_docs([]), bench).count() == 0
    assert decontaminate.contaminated(docs, bench.limit(0)).count() == 0


def test_items_that_share_an_id_are_all_searched(spark, make_docs):
    texts = ["the quick brown fox jumps over the lazy dog", "a second question that has the same number", "an item without any number at all", "one more item without a number"]
    bench = spark.createDataFrame(list(zip([0, 0, None, None], texts)) + [(0, texts[0].upper() + "  ")], "item_id long, text string")
    docs = make_docs([(k, f"before {t} after") for k, t in enumerate(texts)] + [(9, "clean")])
    for block_bytes in (8 << 20, 60):
        got = decontaminate.contaminated(docs, bench, block_bytes=block_bytes).collect()
        assert sorted((r.doc_id, str(r.item_id)) for r in got) == [(0, "0"), (1, "0"), (2, "None"), (3, "None")]
        assert [r.doc_id for r in decontaminate.decontaminate(docs, bench, block_bytes=block_bytes).collect()] == [9]
