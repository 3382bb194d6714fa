"""Quality classifier: a linear-chain conditional random field labels every line good or bad.

A line is seen through a few shares (capitals, symbols, bars, repeated words, digits, lengths) of itself and of its two
neighbours; two transition weights tie neighbouring labels. Forward and backward sums give each line's probability of
being good, and the document's score is their mean weighted by line length.

Training: lines carry their document's label; at most MAX_DOCS labelled documents with at most MAX_LINES lines in all, chosen by
a hash of the id, are fitted on the driver by gradient ascent. Only the lines' features travel there, no text (68 bytes a line). Scoring runs
over whole texts in Arrow batches, without a shuffle.

Edge cases: an empty table gives no rows; a very long text is a slice of its own, and too long for MAX_LINES it isn't fitted; empty lines have no weight; null texts and texts without a visible line get the smoothed share of good ones
among such texts in training (one half if there are none); without labels every score is one half; repeated rows and ties
are scored alike; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .kernels import SPACE, Words, slices, string_views, tidy

common.by_value(__name__)

#: Labelled documents used for fitting, and their lines in all, at most.
MAX_DOCS, MAX_LINES = 3000, 200_000
THRESHOLD = 0.3
FOLDS, HELD_OUT = 5, 0
_SYMBOLS = b"#$%&*~^_=<>@\\+{}[]"
_BASE = 17


def _class(members) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(members)] = True
    return out


_UPPER, _LOWER, _DIGIT = _class(range(65, 91)), _class([*range(97, 123), *range(0xC3, 0xF5)]), _class(range(48, 58))
_SYMBOL, _BAR, _SHOUT, _STOP = _class(_SYMBOLS), _class(b"|"), _class(b"!"), _class(b".?!:;\"')")


def own_features(data: np.ndarray, offsets: np.ndarray, tables: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(features of the line itself, byte lengths, document) of the visible lines of a slice; offsets from 0."""
    n = len(data)
    if not n:
        return np.zeros((0, _BASE), np.float32), np.zeros(0), np.zeros(0, np.int64)
    breaks = (data == 10) | (data == 13)
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    start = np.flatnonzero(edge[:n] | np.concatenate(([True], breaks[:-1])))
    words = Words(data, offsets, tables)
    line_of = np.searchsorted(start, words.start, side="right") - 1
    n_words = np.bincount(line_of, minlength=len(start)).astype(np.float32)
    shown = n_words > 0
    total = lambda mask: np.add.reduceat(mask, start, dtype=np.int32)[shown].astype(np.float32)
    accented = np.zeros(n, bool)
    accented[1:] = (data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0x9E)
    up, low = total(_UPPER[data] | accented), total(_LOWER[data])
    same = np.zeros(len(words), bool)
    same[1:] = (words.hash[1:] == words.hash[:-1]) & (line_of[1:] == line_of[:-1])
    again = np.bincount(line_of, weights=same, minlength=len(start))[shown].astype(np.float32)
    n_words = n_words[shown]
    size = total(~SPACE[data])
    first = start[shown]
    doc = np.searchsorted(offsets, first, side="right") - 1
    last_word = np.searchsorted(words.start, np.concatenate((start[1:], [n]))) - 1
    stop = _STOP[data[words.end[last_word[shown]] - 1]]
    symbols, bars, shouts, digits = (total(c[data]) / n_words for c in (_SYMBOL, _BAR, _SHOUT, _DIGIT))
    capital = up / np.maximum(up + low, 1)
    again = again / n_words
    f = np.stack([
        np.ones_like(capital), capital, np.minimum(symbols, 3), np.minimum(bars, 1), np.minimum(shouts, 2), np.minimum(digits, 3), again, np.minimum(size / n_words, 30) / 10,
        np.log1p(size) / 10, n_words == 1, stop, capital > 0.6, symbols > 0.3, bars > 0.3, shouts > 0.3, again > 0.3, size / n_words > 15,
    ], axis=1).astype(np.float32)
    return f, size, doc


def with_neighbours(f: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Each line's features, those of the line before and after it in its document, and whether there is none."""
    before, after = np.zeros_like(f), np.zeros_like(f)
    inner = doc[1:] == doc[:-1]
    before[1:][inner] = f[:-1][inner]
    after[:-1][inner] = f[1:][inner]
    ends = np.stack([before[:, 0] == 0, after[:, 0] == 0, (before[:, 0] == 0) & (after[:, 0] == 0)], axis=1).astype(np.float32)
    return np.concatenate([f, before, after, ends], axis=1)


def line_features(data: np.ndarray, offsets: np.ndarray, tables: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(features, byte lengths, document) of the visible lines of a slice; offsets from 0."""
    f, size, doc = own_features(data, offsets, tables)
    return with_neighbours(f, doc), size, doc


class Chains:
    """Chains of different lengths, longest first, as a step-by-step layout."""

    def __init__(self, doc: np.ndarray):
        first = np.flatnonzero(np.concatenate(([True], doc[1:] != doc[:-1]))) if len(doc) else np.zeros(0, np.int64)
        length = np.diff(np.concatenate((first, [len(doc)])))
        order = np.argsort(-length, kind="stable")
        self.first, self.length = first[order], length[order]
        longest = int(self.length[0]) if len(first) else 0
        self.active = np.searchsorted(-self.length, -np.arange(1, longest + 1), side="right")

    def steps(self):
        for t, n in enumerate(self.active):
            yield self.first[:n] + t


def forward_backward(u: np.ndarray, chains: Chains, t: np.ndarray, start: float) -> tuple[np.ndarray, np.ndarray]:
    """Log odds of label 1 from the left (with the line itself) and from the right; t[i, j]: weight of i before j."""
    a, b = np.zeros_like(u), np.zeros_like(u)
    steps = list(chains.steps())
    for k, at in enumerate(steps):
        if k == 0:
            a[at] = u[at] + start
        else:
            p = a[at - 1]
            a[at] = u[at] + np.logaddexp(p + t[1, 1], t[0, 1]) - np.logaddexp(p + t[1, 0], t[0, 0])
    for at in reversed(steps[1:]):
        c = u[at] + b[at]
        b[at - 1] = np.logaddexp(c + t[1, 1], t[1, 0]) - np.logaddexp(c + t[0, 1], t[0, 0])
    return a, b


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -60, 60)))


def fit(x: np.ndarray, y: np.ndarray, doc: np.ndarray, rounds: int = 120, decay: float = 2e-3) -> dict:
    """Maximises the conditional likelihood (Adam); x: features, y: 0 or 1 a line, doc: chain of each line."""
    mean, spread = x.mean(0), x.std(0) + 1e-6
    mean[spread < 1e-5] = 0
    spread[spread < 1e-5] = 1
    z = ((x - mean) / spread).astype(np.float64)
    chains = Chains(doc)
    inner = np.flatnonzero(doc[1:] == doc[:-1])
    heads = np.sort(chains.first)
    w, t, s, bias = np.zeros(z.shape[1]), np.zeros((2, 2)), 0.0, 0.0
    theta = np.concatenate([w, t.ravel(), [s, bias]])
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    seen = np.zeros((2, 2))
    np.add.at(seen, (y[inner], y[inner + 1]), 1)
    n = max(1, len(heads))
    for step in range(1, rounds + 1):
        w, t, s, bias = theta[:-6], theta[-6:-2].reshape(2, 2), theta[-2], theta[-1]
        u = z @ w + bias
        a, b = forward_backward(u, chains, t, s)
        p = _sigmoid(a + b)
        left, right = a[inner], u[inner + 1] + b[inner + 1]
        joint = np.stack([np.full(len(inner), t[0, 0]), right + t[0, 1], left + t[1, 0], left + right + t[1, 1]])
        joint = np.exp(joint - joint.max(0)) if len(inner) else joint
        joint = (joint / np.maximum(joint.sum(0), 1e-300)).sum(1).reshape(2, 2)
        g = np.concatenate([z.T @ (y - p), (seen - joint).ravel(), [(y[heads] - p[heads]).sum(), (y - p).sum()]]) / n
        g[:-2] -= decay * theta[:-2]
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        theta = theta + 0.08 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return {"w": theta[:-6] / spread, "bias": float(theta[-1] - (theta[:-6] / spread) @ mean), "t": theta[-6:-2].reshape(2, 2).tolist(), "start": float(theta[-2])}


def score_slice(data: np.ndarray, offsets: np.ndarray, model: dict, tables: dict):
    """(document scores, line probabilities, line documents, line lengths)"""
    n = len(offsets) - 1
    out = np.full(n, model["empty"])
    x, size, doc = line_features(data, offsets, tables)
    if not len(doc) or "w" not in model:
        return out, np.zeros(0), doc, size
    a, b = forward_backward(x @ np.asarray(model["w"]) + model["bias"], Chains(doc), np.asarray(model["t"]), model["start"])
    p = _sigmoid(a + b)
    weight = np.bincount(doc, weights=size, minlength=n)
    told = np.bincount(doc, weights=size * p, minlength=n)
    has = weight > 0
    out[has] = told[has] / weight[has]
    return np.clip(out, 0, 1), p, doc, size


def _feature_rows(batches):
    """The own features of the lines of each document, as bytes."""
    tables: dict = {}
    for batch in batches:
        data, offs = string_views(batch.column("text"))
        for lo, hi in slices(offs):
            f, _, doc = own_features(data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo], tables)
            ends = np.searchsorted(doc, np.arange(hi - lo + 1))
            blobs = [f[a:b].tobytes() for a, b in zip(ends[:-1], ends[1:])]
            yield pa.RecordBatch.from_arrays([batch.column(c).slice(lo, hi - lo) for c in ("place", "th", "quality")] + [pa.array(np.diff(ends)), pa.array(blobs, pa.binary())], names=["place", "th", "quality", "lines", "features"])


def train(docs: DataFrame, labels: DataFrame, max_docs: int = MAX_DOCS, max_lines: int = MAX_LINES) -> dict:
    """Fits the field on labelled documents outside the held-out fold."""
    known = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull() & (F.pmod(common.crc_of_id(), F.lit(FOLDS)) != HELD_OUT))
    known = known.groupBy("doc_id").agg(F.min("quality").alias("quality")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_docs)
    sample = docs.select("doc_id", "text").join(F.broadcast(known), "doc_id")  # at most max_docs ids
    rows = sample.select(F.xxhash64("doc_id").alias("place"), F.xxhash64("text").alias("th"), F.col("quality").cast("long").alias("quality"), "text")
    rows = common.spill(rows.mapInArrow(tidy(_feature_rows), "place bigint, th bigint, quality bigint, lines bigint, features binary"), "quality-lines")
    order = ["place", "th", "quality"]
    few = rows.select(*order, "lines").where(F.col("lines") <= max_lines).orderBy(*order).limit(max_docs).collect()  # max_docs rows of numbers
    taken = int((np.cumsum([r["lines"] for r in few], dtype=np.int64) <= max_lines).sum())
    if not taken:
        return {"empty": 0.5}
    here = F.struct(*order) <= F.struct(*[F.lit(few[taken - 1][c]).cast("long") for c in order])
    got = rows.where(here & (F.col("lines") <= max_lines)).orderBy(*order).limit(taken).collect()  # max_lines lines of features
    common.release(rows)
    y_doc = np.array([r["quality"] for r in got], np.int64)
    n = np.array([r["lines"] for r in got], np.int64)
    model = {"empty": float((1 + y_doc[n == 0].sum()) / (2 + (n == 0).sum()))}
    doc = np.repeat(np.arange(len(got)), n)
    if len(doc):
        f = np.concatenate([np.frombuffer(r["features"], np.float32).reshape(-1, _BASE) for r in got])
        model |= fit(with_neighbours(f, doc), y_doc[doc], doc)
    return model


def scorer(model: dict, inside: tuple[str, int] | None = None):
    """inside: the struct column, and the place in it, that hold the text instead of a column of its own."""
    views, cut = string_views, slices

    def run(batches):
        tables: dict = {}
        for batch in batches:
            data, offs = views(batch.column("text") if inside is None else batch.column(inside[0]).field(inside[1]))
            out = np.full(batch.num_rows, model["empty"])
            for lo, hi in cut(offs):
                out[lo:hi] = score_slice(data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo], model, tables)[0]
            names = [c for c in batch.schema.names if c != "text"]
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in names], pa.array(out)], names=[*names, "score"])

    return run


def line_labeller(model: dict):
    views = string_views

    def run(batches):
        tables: dict = {}
        for batch in batches:
            data, offs = views(batch.column("text"))
            for i in range(batch.num_rows):
                _, p, _, size = score_slice(data[offs[i] : offs[i + 1]], np.array([0, offs[i + 1] - offs[i]]), model, tables)
                ids = batch.column("doc_id").slice(i, 1).take(pa.array(np.zeros(len(p), np.int64)))
                yield pa.RecordBatch.from_arrays([ids, pa.array(np.arange(len(p))), pa.array(size.astype(np.int64)), pa.array(p.astype(float)), pa.array(p >= 0.5)], names=["doc_id", "line", "size", "good_probability", "good"])

    return run


def score(docs: DataFrame, model: dict) -> DataFrame:
    """(doc_id, score)"""
    rows = docs.select("doc_id", "text")
    return rows.mapInArrow(tidy(scorer(model)), f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, score double")


def label_lines(docs: DataFrame, model: dict) -> DataFrame:
    """(doc_id, line, size, good_probability, good), one row a visible line."""
    rows = docs.select("doc_id", "text")
    return rows.mapInArrow(line_labeller(model), f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, line bigint, size bigint, good_probability double, good boolean")


def keep_good(docs: DataFrame, model: dict, threshold: float = THRESHOLD) -> DataFrame:
    """The rows whose score reaches the threshold, columns unchanged; the text is scored where it lies, in its row."""
    names = docs.columns
    rows = docs.select(F.struct(*[docs[c] for c in names]).alias("row"))
    kind = rows.schema["row"].dataType.simpleString()
    return rows.mapInArrow(tidy(scorer(model, ("row", common.place_of(docs, "text")))), f"row {kind}, score double").where(F.col("score") >= threshold).select("row.*")


def op1_quality_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    model = train(docs, common.table(spark, sf_dir, "labels"))
    out = score(docs, model)
    return out.select("doc_id", (F.pmod(common.crc_of_id(), F.lit(FOLDS)) == HELD_OUT).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
