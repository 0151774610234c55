"""Toxicity by a classifier chain of sparse linear models.

The categories are predicted one after another; the model of each category sees the hashed words
and word stems of the text and the probabilities that the chain gave for the earlier categories. When it
learns, those probabilities come from models that did not see the row (out-of-fold predictions over
FOLDS folds), so a later model learns how far earlier ones can be trusted on new rows.

The labels table has two judgements per document; the chain's default order is low quality first,
then toxic. More label columns extend the chain.

Learning takes at most SAMPLE labelled documents, in the order of an id digest (documented
bound); the predictor runs over every whole text as an Arrow map without any shuffle.

Defined cases: null or empty texts have no features and get the prior; labels that are null or
contradict each other teach nothing for that category; a category with one class only learned
gets the constant share; ids that are null match no label; repeated rows are scored each, and learned
each if their id has a label; very long texts are scored whole; a probability of exactly CUT counts as
toxic; kept columns that are called like the new ones are refused; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftlattice.llm.shared import TOKEN_BYTE, Hasher, mix, row_slices, spans, text_buffer, text_map

SAMPLE = 8_000
FOLDS = 5
BITS = 20
#: A word teaches only if so many sampled documents hold it.
MIN_DOCS = 4
EVIDENCE = 15.0
STEMS = (4, 5, 6)
CHAIN = ("low_quality", "toxic")
CUT = 0.5

_HASHER = Hasher(5)


def features(column) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashed words and word stems per text: feature numbers, and each text's first entry (n + 1).

    Stems are the first STEMS bytes of longer words, so inflected and compound forms share features.
    """
    raw, offsets = text_buffer(pc.utf8_lower(column))
    start, end, first = spans(raw, offsets, TOKEN_BYTE)
    n = len(offsets) - 1
    text = np.repeat(np.arange(n, dtype=np.int64), np.diff(first))
    found = [(text, _HASHER.words(raw, start, end))]
    for k in STEMS:
        longer = end - start > k
        found.append((text[longer], mix(_HASHER.words(raw, start[longer], start[longer] + k) + np.uint64(k))))
    value = np.unique(np.concatenate([(t << BITS) | (v >> np.uint64(64 - BITS)).astype(np.int64) for t, v in found]))
    return value & ((1 << BITS) - 1), np.searchsorted(value >> BITS, np.arange(n + 1))


def row_sums(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0.0], np.cumsum(values)])
    return total[first[1:]] - total[first[:-1]]


def sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def word_evidence(index: np.ndarray, row: np.ndarray, y: np.ndarray, width: int) -> np.ndarray:
    """Likelihood-ratio statistic (one degree of freedom) of each word's presence against the label."""
    a = np.bincount(index, y[row], width)  # present and positive
    n = np.bincount(index, minlength=width).astype(float)
    pos, every = y.sum(), float(len(y))
    cells = ((a, n * pos / every), (n - a, n * (every - pos) / every), (pos - a, (every - n) * pos / every), ((every - pos) - (n - a), (every - n) * (every - pos) / every))
    return 2 * sum(np.where(seen > 0, seen * np.log(np.maximum(seen, 1e-12) / np.maximum(due, 1e-12)), 0.0) for seen, due in cells)


class Linear:
    """Logistic regression on hashed words and a few dense columns; full-batch AdaGrad with an L2 term.

    Only words whose presence says something about the label (evidence of EVIDENCE or more) enter.
    """

    def __init__(self, steps: int = 150, rate: float = 0.3, decay: float = 1e-4):
        self.steps, self.rate, self.decay = steps, rate, decay

    def fit(self, index: np.ndarray, first: np.ndarray, dense: np.ndarray, y: np.ndarray, width: int) -> Linear:
        share = float(np.clip(y.mean(), 1e-4, 1 - 1e-4)) if len(y) else 0.5
        self.bias, self.w, self.v = float(np.log(share / (1 - share))), np.zeros(width), np.zeros(dense.shape[1])
        if len(set(y.tolist())) < 2:
            return self
        row = np.repeat(np.arange(len(y)), np.diff(first))
        self.tells = word_evidence(index, row, y, width) >= EVIDENCE
        told = self.tells[index]
        first, index, row = np.concatenate([[0], np.cumsum(told)])[first], index[told], row[told]
        gw, gv, gb = np.full(width, 1e-8), np.full(len(self.v), 1e-8), 1e-8
        for _ in range(self.steps):
            miss = (sigmoid(self.log_odds(index, first, dense)) - y) / len(y)
            dw = np.bincount(index, miss[row], width) + self.decay * self.w
            dv, db = dense.T @ miss + self.decay * self.v, float(miss.sum())
            gw, gv, gb = gw + dw**2, gv + dv**2, gb + db**2
            self.w -= self.rate * dw / np.sqrt(gw)
            self.v -= self.rate * dv / np.sqrt(gv)
            self.bias -= self.rate * db / np.sqrt(gb)
        return self

    def log_odds(self, index, first, dense):
        return self.bias + row_sums(self.w[index], first) + dense @ self.v


def take_rows(index: np.ndarray, first: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    size = np.diff(first)[rows]
    at = np.repeat(first[:-1][rows] - (np.cumsum(size) - size), size) + np.arange(size.sum())
    return index[at], np.concatenate([[0], np.cumsum(size)])


def fit_chain(index: np.ndarray, first: np.ndarray, labels: dict[str, np.ndarray], fold: np.ndarray) -> dict:
    """labels: per category 0, 1 or -1 (unknown). Features are renumbered to those worth learning."""
    often = np.bincount(index, minlength=1 << BITS) >= MIN_DOCS
    place = np.where(often, np.cumsum(often) - 1, -1)
    known = place[index] >= 0
    held = np.concatenate([[0], np.cumsum(known)])
    index, first, width = place[index][known], held[first], max(1, int(often.sum()))
    earlier = np.zeros((len(first) - 1, 0))
    models = []
    for y in labels.values():
        rows = np.flatnonzero(y >= 0)
        out_of_fold = np.zeros(len(y))
        for k in range(FOLDS):
            train, test = rows[fold[rows] != k], np.flatnonzero(fold == k)
            model = Linear().fit(*take_rows(index, first, train), earlier[train], y[train].astype(float), width)
            out_of_fold[test] = sigmoid(model.log_odds(*take_rows(index, first, test), earlier[test]))
        models.append(Linear().fit(*take_rows(index, first, rows), earlier[rows], y[rows].astype(float), width))
        earlier = np.column_stack([earlier, out_of_fold])
    full = np.zeros((len(models), 1 << BITS), np.float32)
    for k, model in enumerate(models):
        full[k, often] = model.w[: int(often.sum())]
    return {"names": list(labels), "weights": full, "bias": [m.bias for m in models], "later": [m.v for m in models]}


def chain_chances(model: dict, index: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Probability of each category, each fed to the models of the later ones."""
    out = np.zeros((len(first) - 1, 0))
    for k in range(len(model["names"])):
        odds = model["bias"][k] + row_sums(model["weights"][k][index].astype(np.float64), first) + out @ model["later"][k]
        out = np.column_stack([out, sigmoid(odds)])
    return out


def learn(docs: DataFrame, labels: DataFrame, chain=CHAIN, sample: int = SAMPLE) -> dict:
    """Fit the chain on a bounded sample of labelled documents. labels: doc_id and 0/1 columns named as the chain."""
    one = labels.where("doc_id IS NOT NULL").groupBy("doc_id").agg(*[F.when(F.min(c) == F.max(c), F.min(c)).alias(c) for c in chain])
    picked = one.orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id").limit(sample)

    def run(batches):
        for batch in batches:
            index, first = features(batch.column("text"))
            blobs = pa.array([index[a:b].astype(np.int32).tobytes() for a, b in zip(first[:-1], first[1:])], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(batch.schema.names.index(c)) for c in ("doc_id", *chain)] + [blobs], ["doc_id", *chain, "words"])

    # the sample is bounded by `sample` rows, so it is broadcast to the documents
    joined = docs.select("doc_id", F.col("text").cast("string").alias("text")).where("text IS NOT NULL").join(F.broadcast(picked), "doc_id")
    kinds = ", ".join(f"{c} long" for c in chain)
    rows = joined.select("doc_id", "text", *[F.col(c).cast("long").alias(c) for c in chain]).mapInArrow(run, f"doc_id {dict(joined.dtypes)['doc_id']}, {kinds}, words binary").collect()
    rows.sort(key=lambda r: (r.doc_id, bytes(r.words)))
    parts = [np.frombuffer(r.words, np.int32).astype(np.int64) for r in rows]
    first = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)
    index = np.concatenate([np.zeros(0, np.int64), *parts])
    given = {c: np.array([-1 if r[c] is None else int(r[c] > 0) for r in rows], np.int64) for c in chain}
    return fit_chain(index, first, given, np.array([zlib.crc32(str(r.doc_id).encode()) % FOLDS for r in rows], np.int64))


def predict(docs: DataFrame, model: dict, keep=("doc_id",), cut: float = CUT) -> DataFrame:
    """docs(text, *keep) -> (*keep, p_<category> ..., <last category> boolean)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = model["names"]

    def run():
        def columns(texts):
            chance = np.concatenate([np.zeros((0, len(names))), *[chain_chances(shared.value, *features(texts.slice(a, b - a))) for a, b in row_slices(texts)]])
            return *[pa.array(chance[:, k]) for k in range(len(names))], pa.array(chance[:, -1] >= cut)

        return columns

    return text_map(docs, keep, "".join(f"p_{c} double, " for c in names) + f"{names[-1]} boolean", run)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", (1 - F.col("quality")).alias("low_quality"), "toxic")
    return predict(docs, learn(docs, labels))
