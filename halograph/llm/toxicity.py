"""Toxicity severity by cumulative-link (proportional odds) regression on sparse word features.

All thresholds share one weight vector: P(grade > k) = logistic(w.x - cut[k]). Labels say only toxic or not, so grades
are set before the model is fitted, and by other documents than the graded one: training documents are in two folds, and a
toxic document's grade is the number of different words (1, 2, 3 or more) that the other fold alone shows to tell toxic
documents. Documents of label 0 are grade 0. The result is the expected grade, and a document is toxic when grade 1 or
more is likelier than not.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halograph.llm.common import LOWER_BYTES, runs, slices, span_hashes, text_bytes, worker_store
from halograph.llm.labelled import held_out, sample
from halograph.llm.quality import Adam, _sigmoid

#: Labelled documents of each class that the model is fitted on, at most.
PER_CLASS = 4000
#: Labelled texts beyond this size teach nothing, so that the driver holds at most 2 * PER_CLASS * TRAIN_BYTES.
TRAIN_BYTES = 32 << 10
GRADES = 4
#: A word is weighed if so many of the documents hold it and its log odds are so many deviations from none.
LEAST_DOCS, LEAST_Z = 3, 2.6
SLICE_BYTES = 2 << 20
_LETTER = np.zeros(256, bool)
_LETTER[[*range(65, 91), *range(97, 123), *range(128, 256)]] = True


def document_words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(document, word hash) of each word: letters A-Z in either case and all bytes of letters beyond ASCII."""
    starts, ends, doc = runs(_LETTER[data], offsets)
    return doc, span_hashes(LOWER_BYTES[data], starts, ends)


def _deviations(at: np.ndarray, doc: np.ndarray, labels: np.ndarray, n_words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(log odds ratio of each word in units of its own deviation, documents of label 1 and of label 0 that hold it)."""
    n1, n0 = labels.sum(), (1 - labels).sum()
    with1, with0 = np.bincount(at, labels[doc], n_words), np.bincount(at, 1 - labels[doc], n_words)
    p1, p0 = (with1 + 0.5) / (n1 + 1), (with0 + 0.5) / (n0 + 1)
    return (np.log(p1 / (1 - p1)) - np.log(p0 / (1 - p0))) / np.sqrt(1 / (with1 + 0.5) + 1 / (with0 + 0.5)), with1, with0


def _grades(at: np.ndarray, doc: np.ndarray, labels: np.ndarray, n_words: int) -> np.ndarray:
    """Grades of the training documents, those of a fold by the telling words of the other."""
    fold = np.arange(len(labels)) % 2
    hits = np.zeros(len(labels))
    for f in (0, 1):
        teach = fold[doc] != f
        z, with1, with0 = _deviations(at[teach], doc[teach], np.where(fold != f, labels, 0), n_words)
        n1, n0 = labels[fold != f].sum(), (1 - labels)[fold != f].sum()
        telling = (with1 * n0 >= 4 * with0 * n1) & (z > 2.5) & (with1 >= 2)
        own = ~teach & telling[at]
        hits += np.bincount(doc[own], minlength=len(labels))
    return np.where(labels == 1, np.clip(hits, 1, GRADES - 1), 0).astype(int)


def likelihood(z: np.ndarray, cuts: np.ndarray, grade: np.ndarray, weight: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """(weighted mean log loss of the grades, its slope in z, its slope in the cuts) of the cumulative-link model."""
    above = _sigmoid(z[:, None] - cuts)
    edges = np.concatenate([np.ones((len(z), 1)), above, np.zeros((len(z), 1))], 1)
    row = np.arange(len(z))
    p = np.maximum(edges[row, grade] - edges[row, grade + 1], 1e-12)
    slope = np.concatenate([np.zeros((len(z), 1)), above * (1 - above), np.zeros((len(z), 1))], 1)
    low, high = slope[row, grade] / p, slope[row, grade + 1] / p
    by_cut = np.zeros((len(z), len(cuts) + 2))
    np.add.at(by_cut, (row, grade), weight * low)
    np.add.at(by_cut, (row, grade + 1), -weight * high)
    return float(-(weight * np.log(p)).sum()), -weight * (low - high), by_cut[:, 1:-1].sum(0)


def fit(rows: list[tuple[np.ndarray, int]]) -> dict:
    """rows: distinct word hashes of a document, and its label 0 or 1. Without both labels every severity is 0."""
    labels = np.array([y for _, y in rows])
    if len(set(labels.tolist())) < 2:
        return {"words": np.zeros(0, np.uint64), "w": np.zeros(0), "cuts": np.array([30.0, 31.0, 32.0])}
    words, at = np.unique(np.concatenate([x for x, _ in rows]), return_inverse=True)
    doc = np.repeat(np.arange(len(rows)), [len(x) for x, _ in rows])
    grade = _grades(at, doc, labels, len(words))
    z, with1, with0 = _deviations(at, doc, labels, len(words))
    used = np.flatnonzero((with1 + with0 >= LEAST_DOCS) & (np.abs(z) >= LEAST_Z))
    column = np.full(len(words), -1)
    column[used] = np.arange(len(used))
    here = column[at] >= 0
    doc, at = doc[here], column[at][here]
    # cuts rise: the first is free, the others are steps of a positive size
    both = np.concatenate([np.zeros(len(used)), [1.0], np.log([1.5, 1.5])])
    adam = Adam(len(both), 0.1)
    weight = np.where(labels == 1, 0.5 / labels.sum(), 0.5 / (1 - labels).sum())
    unpack = lambda x: (x[: len(used)], x[len(used)] + np.concatenate([[0], np.cumsum(np.exp(x[len(used) + 1 :]))]))
    for _ in range(200):
        w, cuts = unpack(both)
        _, g_z, g_cut = likelihood(np.bincount(doc, w[at], len(rows)), cuts, grade, weight)
        # the penalty holds back words that occur by chance in a handful of documents
        g_w = np.bincount(at, g_z[doc], len(used)) + 4e-4 * w
        adam.step(both, np.concatenate([g_w, [g_cut.sum()], g_cut[1:][::-1].cumsum()[::-1] * np.exp(both[len(used) + 1 :])]))
    w, cuts = unpack(both)
    return {"words": words[used], "w": w, "cuts": cuts}


class Scorer:
    BITS = 20

    def __init__(self, model: dict):
        self.model = model
        self.table = np.zeros(1 << self.BITS, bool)
        self.table[model["words"] >> np.uint64(64 - self.BITS)] = True

    def score(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(expected grade, probability of grade 1 or more) of each document."""
        n, words = len(offsets) - 1, self.model["words"]
        z = np.zeros(n)
        if len(words) and len(data):
            doc, h = document_words(data, offsets)
            near = self.table[h >> np.uint64(64 - self.BITS)]
            doc, h = doc[near], h[near]
            at = np.searchsorted(words, h)
            at[at == len(words)] = 0
            same = words[at] == h
            pair = np.unique(doc[same] * np.int64(len(words)) + at[same])
            z = np.bincount(pair // len(words), self.model["w"][pair % len(words)], n)
        over = _sigmoid(z[:, None] - self.model["cuts"])
        return over.sum(1), over[:, 0]


def _distinct_words(batches):
    for batch in batches:
        for part in slices(batch, "text", SLICE_BYTES):
            data, offsets = text_bytes(part.column(1))
            doc, h = document_words(data, offsets)
            cut = np.searchsorted(doc, np.arange(part.num_rows + 1))
            own = [np.unique(h[a:b]).tobytes() for a, b in zip(cut, cut[1:])]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(own, pa.binary()), part.column(2)], names=["doc_id", "words", "label"])


def train(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> dict:
    short = docs.filter(F.coalesce(F.octet_length("text"), F.lit(0)) <= TRAIN_BYTES)
    rows = sample(short, labels, "toxic", per_class).mapInArrow(_distinct_words, "doc_id long, words binary, label int").collect()
    rows = sorted(rows, key=lambda r: (r.doc_id, bytes(r.words)))
    return fit([(np.frombuffer(r.words, np.uint64), int(r.label)) for r in rows])


def severity(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, severity (expected grade, 0 to 3), score (probability of grade 1 or more), toxic (score at least a half).

    A null or empty text has no words and the severity of the cuts alone. Repeated rows score alike, a null doc_id stays
    null, other columns are not read, an empty table gives an empty result, texts are read whole.
    """
    key = uuid.uuid4().hex

    def run(batches):
        store = worker_store("toxicity")
        if store.get("key") != key:
            store.update(key=key, scorer=Scorer(model))
        for batch in batches:
            for part in slices(batch, "text", SLICE_BYTES):
                grade, p = store["scorer"].score(*text_bytes(part.column(1)))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(grade, pa.float64()), pa.array(p, pa.float64()), pa.array(p >= 0.5)], names=["doc_id", "severity", "score", "toxic"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, severity double, score double, toxic boolean")


def op4_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return severity(docs, model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "severity", "score", "toxic")
