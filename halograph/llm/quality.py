"""Document quality from a linear-chain conditional random field over lines.

Every line is good or bad. Its features are shares of byte classes, repeated words and the same of the lines beside it;
the chain couples neighbouring labels. Lines learn from the label of their document; lines of bad documents that look
good by themselves are then taken as good and the chain is fitted once more. A document's quality is the mean marginal
of its lines, weighted by their length, mapped to a probability by a logistic curve fitted on the same rows.
"""

from __future__ import annotations


import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halograph.llm.common import LOWER_BYTES, WORD_BREAK, runs, slices, span_hashes, text_bytes
from halograph.llm.labelled import held_out, sample

#: Labelled documents of each class that the model is fitted on, at most.
PER_CLASS = 800
THRESHOLD = 0.7
#: Labelled texts beyond this size teach nothing, so that the driver holds at most 2 * PER_CLASS * TRAIN_BYTES.
TRAIN_BYTES = 32 << 10
SLICE_BYTES = 2 << 20
#: Memory of a line while a slice is scored, so that slices are bounded by lines too.
LINE_BYTES = 700
#: Documents of more lines are scored in segments of so many, with the messages of the chain carried between them.
SEGMENT = 1 << 12

_CLASSES = [b"#$%&*+/<=>@[\\]^_`{}~", b"|", b"!?", b"0123456789", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz", b" \t", b".,;:'\"-()"]
_IS = np.zeros((len(_CLASSES) + 1, 256), np.uint8)
for _k, _members in enumerate(_CLASSES):
    _IS[_k, list(_members)] = 1
_IS[len(_CLASSES), 128:] = 1
N_OWN = 17
N_FEATURES = 3 * N_OWN + 2


def line_bounds(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, first line of each document): lines end at line feeds; an empty text is one empty line."""
    feeds = np.flatnonzero(data == 10)
    starts = np.concatenate([offsets[:-1], feeds + 1])
    doc = np.concatenate([np.arange(len(offsets) - 1), np.searchsorted(offsets, feeds, "right") - 1])
    order = np.lexsort((starts, doc))
    starts, doc = starts[order], doc[order]
    first = np.searchsorted(doc, np.arange(len(offsets)))
    ends = np.empty_like(starts)
    ends[:-1] = starts[1:] - 1
    ends[first[1:] - 1] = offsets[1:]
    return starts, ends, first


def line_features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(features of each line, its length, first line of each document)."""
    starts, ends, first = line_bounds(data, offsets)
    size = (ends - starts).astype(np.float64)
    n = len(starts)
    own = np.zeros((n, N_OWN), np.float32)
    total = np.zeros(len(data) + 1, np.int64)
    for k in range(len(_IS)):
        np.cumsum(_IS[k][data], out=total[1:])
        own[:, k] = (total[ends] - total[starts]) / np.maximum(size, 1)
    words, stops, _ = runs(WORD_BREAK[data], offsets)
    line = np.searchsorted(starts, words, "right") - 1
    count = np.bincount(line, minlength=n)
    h = span_hashes(LOWER_BYTES[data], words, stops)
    again = np.zeros(len(words), np.float32)
    again[1:] = (h[1:] == h[:-1]) & (line[1:] == line[:-1])
    k = len(_IS)
    own[:, k] = np.bincount(line, again, n) / np.maximum(count, 1)
    own[:, k + 1] = np.minimum(size / np.maximum(count, 1), 40) / 10
    own[:, k + 2] = np.log1p(size) / 5
    own[:, k + 3] = count <= 2
    letters = own[:, 4] + own[:, 5]
    own[:, k + 4] = own[:, 4] / np.maximum(letters, 1e-3)
    own[:, k + 5] = own[:, 0] > 0.04
    own[:, k + 6] = own[:, k + 4] > 0.5
    own[:, k + 7] = own[:, k] > 0.2
    own = np.sqrt(own)
    before, after = np.zeros_like(own), np.zeros_like(own)
    before[1:], after[:-1] = own[:-1], own[1:]
    lone_first, lone_last = np.zeros(n, bool), np.zeros(n, bool)
    lone_first[first[:-1]] = True
    lone_last[first[1:] - 1] = True
    before[lone_first], after[lone_last] = 0, 0
    return np.hstack([np.ones((n, 1), np.float32), own, before, after, lone_first[:, None].astype(np.float32)]), size, first


class Chain:
    """Two-state chain; messages are log odds of good against bad, so a step is one scalar a document."""

    def __init__(self, first: np.ndarray):
        counts = np.diff(first)
        self.order = np.argsort(-counts, kind="stable")
        self.starts, self.counts = first[:-1][self.order], counts[self.order]
        longest = int(self.counts[0]) if len(counts) else 0
        self.live = len(counts) - np.searchsorted(self.counts[::-1], np.arange(longest), "right")

    def messages(self, e: np.ndarray, t: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(forward with the line's own evidence, backward without it); t[a, b] is the log potential of a then b."""
        forward, backward = np.zeros(len(e)), np.zeros(len(e))
        for j, m in enumerate(self.live):
            at = self.starts[:m] + j
            if j == 0:
                forward[at] = e[at]
            else:
                a = forward[at - 1]
                forward[at] = e[at] + np.logaddexp(a + t[1, 1], t[0, 1]) - np.logaddexp(a + t[1, 0], t[0, 0])
        for j in range(len(self.live) - 1, 0, -1):
            at = self.starts[: self.live[j]] + j
            b = backward[at] + e[at]
            backward[at - 1] = np.logaddexp(b + t[1, 1], t[1, 0]) - np.logaddexp(b + t[0, 1], t[0, 0])
        return forward, backward


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


class Adam:
    def __init__(self, size: int, rate: float):
        self.m, self.v, self.n, self.rate = np.zeros(size), np.zeros(size), 0, rate

    def step(self, x: np.ndarray, gradient: np.ndarray) -> None:
        self.n += 1
        self.m = 0.9 * self.m + 0.1 * gradient
        self.v = 0.99 * self.v + 0.01 * gradient**2
        x -= self.rate * (self.m / (1 - 0.9**self.n)) / (np.sqrt(self.v / (1 - 0.99**self.n)) + 1e-8)


def _fit_chain(x: np.ndarray, y: np.ndarray, weight: np.ndarray, first: np.ndarray, w: np.ndarray, t: np.ndarray, rounds: int) -> None:
    chain, n = Chain(first), len(x)
    inner = np.ones(n, bool)
    inner[first[:-1]] = False
    right = np.flatnonzero(inner)
    left = right - 1
    adam = Adam(len(w) + 4, 0.08)
    seen = np.zeros((2, 2))
    np.add.at(seen, (y[left].astype(int), y[right].astype(int)), weight[right])
    both = np.concatenate([w, t.ravel()])
    scale = weight.sum()
    for _ in range(rounds):
        w[:], t[:] = both[:-4], both[-4:].reshape(2, 2)
        e = x @ w
        forward, backward = chain.messages(e, t)
        p = _sigmoid(forward + backward)
        g = x.T @ (weight * (p - y)) / scale + 1e-3 * w
        pairs = np.stack([t[0, 0] + 0 * left, t[0, 1] + e[right] + backward[right], forward[left] + t[1, 0], forward[left] + t[1, 1] + e[right] + backward[right]])
        pairs = np.exp(pairs - pairs.max(0))
        pairs *= weight[right] / pairs.sum(0)
        gt = (pairs.sum(1) - seen.ravel()) / scale + 1e-3 * t.ravel()
        adam.step(both, np.concatenate([g, gt]))
    w[:], t[:] = both[:-4], both[-4:].reshape(2, 2)


def fit(texts: list[str], labels: list[int]) -> dict:
    """A model as plain arrays. With labels of one kind only, or none, scores are constant: the share of label 1 or 0.5."""
    if len(set(labels)) < 2:
        return {"constant": float(np.mean(labels)) if labels else 0.5}
    data, offsets = text_bytes(pa.array(texts, pa.large_string()))
    x, size, first = line_features(data, offsets)
    doc = np.repeat(np.arange(len(texts)), np.diff(first))
    truth = np.array(labels, float)
    y = truth[doc]
    # each document weighs the same, shared by its lines in proportion to their length
    bulk = np.bincount(doc, size + 1)
    weight = (size + 1) / bulk[doc]
    x = x.astype(np.float64)
    w, t = np.zeros(x.shape[1]), np.zeros((2, 2))
    adam = Adam(len(w), 0.1)
    for _ in range(80):  # lines on their own first
        adam.step(w, x.T @ (weight * (_sigmoid(x @ w) - y)) / len(texts) + 1e-3 * w)
    looks = x @ w
    worst = np.full(len(texts), np.inf)
    np.minimum.at(worst, doc, looks)
    y = np.where((y == 0) & (looks > 2) & (looks > worst[doc]), 1.0, y)
    _fit_chain(x, y, weight, first, w, t, 30)
    m = np.clip(_mean_marginal(x, size, first, w, t), 1e-6, 1 - 1e-6)
    z = np.stack([np.log(m / (1 - m)), np.ones(len(m))], 1)
    c = np.array([1.0, 0.0])
    for _ in range(30):
        p = _sigmoid(z @ c)
        h = (z * (p * (1 - p))[:, None]).T @ z + 0.05 * np.eye(2)
        c -= np.linalg.solve(h, z.T @ (p - truth) + 0.05 * (c - [1, 0]))
    return {"w": w, "t": t, "curve": c}


def _mean_marginal(x, size, first, w, t) -> np.ndarray:
    e = x.astype(np.float64) @ w
    forward, backward = Chain(first).messages(e, t)
    doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
    return np.bincount(doc, _sigmoid(forward + backward) * (size + 1), len(first) - 1) / np.bincount(doc, size + 1, len(first) - 1)


def _segments(text: np.ndarray, most: int):
    """(log odds features, sizes) of a text's lines, so many at a time; neighbours across a bound are seen as well."""
    feeds = np.flatnonzero(text == 10)
    n = len(feeds) + 1
    start = lambda j: 0 if j <= 0 else int(feeds[j - 1]) + 1
    for a in range(0, n, most):
        b = min(a + most, n)
        low, high = max(a - 1, 0), min(b + 1, n)
        part = text[start(low) : len(text) if high == n else int(feeds[high - 1])]
        x, size, _ = line_features(part, np.array([0, len(part)]))
        if low > 0:  # the first line of the part is not the first of the text
            x[0, -1] = 0
        yield x[a - low : b - low], size[a - low : b - low]


def _chained(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Product of matrices of log weights, of one or of stacks of them, shifted to a largest entry of 0."""
    c = np.logaddexp(a[..., :, 0, None] + b[..., None, 0, :], a[..., :, 1, None] + b[..., None, 1, :])
    return c - c.max((-2, -1), keepdims=True)


def _folded(e: np.ndarray, t: np.ndarray) -> np.ndarray:
    """Product of the steps of all lines in order, by halving."""
    m = t + np.stack([np.zeros(len(e)), e], 1)[:, None, :]
    while len(m) > 1:
        tail = m[len(m) // 2 * 2 :]
        m = np.concatenate([_chained(m[0 : len(m) // 2 * 2 : 2], m[1::2]), tail])
    return m[0]


def long_marginal(text: np.ndarray, w: np.ndarray, t: np.ndarray, most: int = SEGMENT) -> float:
    """What _mean_marginal gives for one text, in memory of a segment of lines.

    Each segment is folded to the matrix that it is to the chain; with the messages that come in from both sides, its own
    lines are then done as a chain of their own.
    """
    folds, heads = [], []
    for k, (x, _) in enumerate(_segments(text, most)):
        e = x.astype(np.float64) @ w
        heads.append(e[0])
        folds.append(_folded(e[1:] if k == 0 else e, t) if len(e) > (k == 0) else None)
    into = [None]  # log weights of the line before each segment
    at = np.array([0.0, heads[0]])
    for f in folds:
        if f is not None:
            at = np.logaddexp(at[0] + f[0], at[1] + f[1])
            at = at - at.max()
        into.append(at)
    back = [np.zeros(2)]
    for f in folds[:0:-1]:
        b = np.logaddexp(f[:, 0] + back[-1][0], f[:, 1] + back[-1][1])
        back.append(b - b.max())
    back.reverse()
    good = bulk = 0.0
    for k, (x, size) in enumerate(_segments(text, most)):
        e = x.astype(np.float64) @ w
        if k:  # the message from before is evidence of the first line
            e[0] += np.logaddexp(into[k][0] + t[0, 1], into[k][1] + t[1, 1]) - np.logaddexp(into[k][0] + t[0, 0], into[k][1] + t[1, 0])
        tail = back[k][1] - back[k][0]
        e[-1] += tail  # and the one from behind is evidence of the last
        forward, backward = _single(e, t)
        good += float((_sigmoid(forward + backward) * (size + 1)).sum())
        bulk += float((size + 1).sum())
    return good / bulk


def _single(e: np.ndarray, t: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """messages of one chain: stretches of about the root of its length side by side, entered with what comes before."""
    n = len(e)
    width = max(1, int(n**0.5))
    rows = -(-n // width)
    padded = np.concatenate([e, np.zeros(rows * width - n)]).reshape(rows, width)

    def run(ev: np.ndarray, t: np.ndarray) -> np.ndarray:
        m = np.broadcast_to(np.array([[0.0, -np.inf], [-np.inf, 0.0]]), (rows, 2, 2))
        for j in range(width):
            m = _chained(m, t + np.stack([np.zeros(rows), ev[:, j]], 1)[:, None, :])
        at, enter = None, np.zeros((rows, 2))
        for r in range(rows):
            enter[r] = 0 if at is None else at
            if at is None:  # the first line has no line before it
                f = _folded(ev[0, 1:], t) if width > 1 else None
                at = np.array([0.0, ev[0, 0]])
                at = at if f is None else np.logaddexp(at[0] + f[0], at[1] + f[1])
            else:
                at = np.logaddexp(at[0] + m[r, 0], at[1] + m[r, 1])
            at = at - at.max()
        out = np.zeros((rows, width))
        a = enter[:, 1] - enter[:, 0]
        for j in range(width):
            step = ev[:, j] + np.logaddexp(a + t[1, 1], t[0, 1]) - np.logaddexp(a + t[1, 0], t[0, 0])
            if j == 0:
                step[0] = ev[0, 0]
            out[:, j] = a = step
        return out

    with np.errstate(invalid="ignore"):
        forward = run(padded, t).ravel()[:n]
        mirrored = np.concatenate([e[::-1], np.zeros(rows * width - n)]).reshape(rows, width)
        backward = run(mirrored, t.T).ravel()[:n][::-1] - e
    return forward, backward


def score(model: dict, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    if "constant" in model or len(offsets) == 1:
        return np.full(len(offsets) - 1, model.get("constant", 0.5))
    if len(offsets) == 2 and np.count_nonzero(data == 10) >= SEGMENT:
        m = np.array([long_marginal(data, model["w"], model["t"])])
    else:
        x, size, first = line_features(data, offsets)
        m = _mean_marginal(x, size, first, model["w"], model["t"])
    m = np.clip(m, 1e-6, 1 - 1e-6)
    return _sigmoid(np.log(m / (1 - m)) * model["curve"][0] + model["curve"][1])


def line_marginals(model: dict, text: str) -> list[tuple[str, float]]:
    """The lines of a text, each with the probability that it is good."""
    data, offsets = text_bytes(pa.array([text], pa.large_string()))
    x, _, first = line_features(data, offsets)
    forward, backward = Chain(first).messages(x.astype(np.float64) @ model["w"], model["t"])
    return list(zip(text.split("\n"), _sigmoid(forward + backward).tolist()))


def train(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> dict:
    short = docs.filter(F.coalesce(F.octet_length("text"), F.lit(0)) <= TRAIN_BYTES)
    rows = sorted(sample(short, labels, "quality", per_class).collect(), key=lambda r: (r.doc_id, r.text))
    return fit([r.text for r in rows], [int(r.label) for r in rows])


def _scores(model: dict, keep: float | None):
    def run(batches):
        for batch in batches:
            for part in slices(batch, "text", SLICE_BYTES, LINE_BYTES):
                got = score(model, *text_bytes(part.column(part.schema.get_field_index("text"))))
                if keep is None:
                    yield pa.RecordBatch.from_arrays([part.column(0), pa.array(got, pa.float64())], names=["doc_id", "score"])
                else:
                    yield part.filter(pa.array(got >= keep))

    return run


def score_documents(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, score of every row. A null text is empty: one empty line. Repeated rows score alike, a null doc_id stays
    null, other columns are not read, an empty table gives an empty result. Texts are read whole: those of very many
    lines are scored in segments, with the same result."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_scores(model, None), "doc_id long, score double")


def keep_good(docs: DataFrame, model: dict, threshold: float = THRESHOLD) -> DataFrame:
    """The rows, all columns, whose text scores at least the threshold."""
    return docs.mapInArrow(_scores(model, threshold), docs.schema)


def op6_quality_crf(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = score_documents(docs, model)
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
