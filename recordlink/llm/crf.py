"""Document quality from a linear-chain conditional random field over lines.

Every line is good or bad.  Its evidence is a vector of facts about itself and the same facts of the lines before and
after; neighbouring labels influence each other through transition weights.  Forward and backward passes give each line's
probability of being good; a document's quality is their mean, weighted by the lines' lengths, put on a scale by two numbers
fitted on training documents.

Training labels are given to documents: all lines of a training document carry its label.  The labelled sample is bounded
(``max_docs`` documents in the order of their hashed ids, up to about ``max_bytes`` bytes of whole texts); scoring covers every row.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Facts of one line, in order.
FACTS = ["empty", "short", "long", "symbols", "digits", "capitals", "repeats", "longest_run", "bars", "word_length", "ends", "urls", "common_words"]
SYMBOL = re.compile(rb"[#*$%&|<>\[\]{}=_~^\\@]")
KEEP_DIGITS = bytes(b for b in range(256) if not 48 <= b <= 57)
KEEP_CAPITALS = bytes(b for b in range(256) if not 65 <= b <= 90)


def line_facts(line: bytes) -> list[float]:
    words = line.split()
    n = len(words)
    size = len(line)
    if not n:
        return [1.0] + [0.0] * (len(FACTS) - 1)
    distinct = len(set(words))
    run = longest = 1
    if distinct < n:
        for a, b in zip(words, words[1:], strict=False):
            run = run + 1 if a == b else 1
            if run > longest:
                longest = run
    return [
        0.0,
        1.0 if n < 5 else 0.0,
        min(1.0, math.log1p(n) / 8),
        min(1.0, 4 * len(SYMBOL.findall(line)) / size),
        min(1.0, 4 * len(line.translate(None, KEEP_DIGITS)) / size),
        min(1.0, 2 * len(line.translate(None, KEEP_CAPITALS)) / size),
        1 - distinct / n,
        (longest - 1) / n,
        words.count(b"|") / n,
        min(1.0, size / n / 20),
        1.0 if line.rstrip()[-1:] in b".!?" else 0.0,
        1.0 if b"://" in line else 0.0,
        sum(len(w) <= 3 for w in words) / n,
    ]


SIZE = 3 * len(FACTS) + 3


def features(lines: list[bytes]) -> np.ndarray:
    """Rows: a bias, a line's facts, those of the lines around it, whether it equals one of them."""
    own = np.array([line_facts(x) for x in lines], np.float32)
    zero = np.zeros((1, own.shape[1]), np.float32)
    before, after = np.concatenate([zero, own[:-1]]), np.concatenate([own[1:], zero])
    same = np.zeros((len(lines), 2), np.float32)
    for i in range(1, len(lines)):
        if lines[i] == lines[i - 1]:
            same[i, 0] = same[i - 1, 1] = 1
    return np.concatenate([np.ones((len(lines), 1), np.float32), own, before, after, same], axis=1)


@dataclass
class Crf:
    """``weights``: evidence for good; ``trans[i, j]``: from label i to j; ``start``; ``slope`` and ``shift`` of the scale."""

    weights: np.ndarray
    trans: np.ndarray
    start: np.ndarray
    slope: float = 1.0
    shift: float = 0.0

    def marginals(self, unary: np.ndarray, offsets: np.ndarray, pairs: bool = False) -> tuple[np.ndarray, np.ndarray | None, np.ndarray | None]:
        """P(good) of each line; if ``pairs``, also the lines that have one before them and their 2 x 2 joint probabilities.

        All documents advance together, longest first, so a step handles those that still have lines.
        """
        lengths = np.diff(offsets)
        order = np.argsort(-lengths, kind="stable")
        first, size = offsets[:-1][order], lengths[order]
        n, top = len(unary), int(size[0]) if len(size) else 0
        active = np.searchsorted(-size, -np.arange(top), side="left")  # documents with more than t lines
        score = np.stack([np.zeros(n), unary], axis=1)
        alpha, beta = np.empty((n, 2)), np.zeros((n, 2))
        for t in range(top):
            at = first[: active[t]] + t
            if t == 0:
                alpha[at] = self.start + score[at]
            else:
                step = alpha[at - 1][:, :, None] + self.trans
                alpha[at] = np.logaddexp(step[:, 0], step[:, 1]) + score[at]
        for t in range(top - 2, -1, -1):
            at = first[: active[t + 1]] + t
            step = self.trans + (score[at + 1] + beta[at + 1])[:, None, :]
            beta[at] = np.logaddexp(step[:, :, 0], step[:, :, 1])
        z_of = np.zeros(len(lengths))
        some = lengths > 0
        ends = offsets[1:][some] - 1
        z_of[some] = np.logaddexp(alpha[ends, 0], alpha[ends, 1])
        z = np.repeat(z_of, lengths)
        good = np.exp(np.clip(alpha[:, 1] + beta[:, 1] - z, -700, 0))
        if not pairs:
            return good, None, None
        inner = np.ones(n, bool)
        inner[offsets[:-1][some]] = False
        at = np.flatnonzero(inner)
        pair = alpha[at - 1][:, :, None] + self.trans + (score[at] + beta[at])[:, None, :] - z[at][:, None, None]
        return good, at, np.exp(np.clip(pair, -700, 0))

    def documents(self, good: np.ndarray, sizes: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Length-weighted means; a document without bytes counts each line alike."""
        owner = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
        weight = sizes + 1e-9
        n = len(offsets) - 1
        return np.bincount(owner, good * weight, n) / np.maximum(np.bincount(owner, weight, n), 1e-12)

    def scale(self, mean: np.ndarray) -> np.ndarray:
        p = np.clip(mean, 1e-6, 1 - 1e-6)
        return 1 / (1 + np.exp(-(self.slope * np.log(p / (1 - p)) + self.shift)))


def _layout(docs: list[list[bytes]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    x = np.concatenate([features(d) for d in docs]) if docs else np.zeros((0, SIZE), np.float32)
    offsets = np.concatenate(([0], np.cumsum([len(d) for d in docs]))).astype(np.int64)
    sizes = np.array([len(line) for d in docs for line in d], float)
    return x, offsets, sizes


def _adam(grad_of, theta: np.ndarray, steps: int, rate: float, project=lambda t: t) -> np.ndarray:
    """Steps up the gradient; ``project`` puts theta back among the allowed ones after each."""
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for k in range(1, steps + 1):
        g = grad_of(theta)
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        theta = project(theta + rate * (m / (1 - 0.9**k)) / (np.sqrt(v / (1 - 0.999**k)) + 1e-8))
    return theta


def fit(docs: list[list[bytes]], labels: list[int], steps: int = 200, rate: float = 0.1, l2: float = 1e-3, max_stay: float = 1.5) -> Crf:
    """Maximum conditional likelihood of the line labels, each document weighing alike within its class.

    As all lines of a training document share a label, the weights for staying in a label would only grow; they are kept
    within ``max_stay`` at every step, so that the other weights are the best beside them.
    """
    x, offsets, sizes = _layout(docs)
    y = np.array(labels, float)
    if not len(docs):
        return Crf(np.zeros(SIZE), np.zeros((2, 2)), np.zeros(2))
    lengths = np.diff(offsets)
    per_class = np.where(y == 1, (y == 1).sum(), (y == 0).sum())
    doc_weight = 0.5 / per_class
    line_y, line_w = np.repeat(y, lengths), np.repeat(doc_weight / lengths, lengths)
    first = offsets[:-1]

    def unfold(theta: np.ndarray) -> Crf:
        a = theta[SIZE:]
        return Crf(theta[:SIZE], np.array([[a[0], 0.0], [0.0, a[1]]]), np.array([0.0, a[2]]))

    def grad(theta: np.ndarray) -> np.ndarray:
        model = unfold(theta)
        good, at, pair = model.marginals(x @ model.weights, offsets, pairs=True)
        rest = (line_y - good) * line_w
        stay0 = ((1 - line_y[at]) - pair[:, 0, 0]) * line_w[at]
        stay1 = (line_y[at] - pair[:, 1, 1]) * line_w[at]
        g = np.concatenate([x.T @ rest, [stay0.sum(), stay1.sum(), rest[first].sum()]])
        return g - l2 * theta

    most = np.full(SIZE + 3, np.inf)
    most[SIZE : SIZE + 2] = max_stay
    model = unfold(_adam(grad, np.zeros(SIZE + 3), steps, rate, lambda t: np.clip(t, -most, most)))
    good, _, _ = model.marginals(x @ model.weights, offsets)
    p = np.clip(model.documents(good, sizes, offsets), 1e-6, 1 - 1e-6)
    z = np.log(p / (1 - p))

    def grad_scale(t: np.ndarray) -> np.ndarray:
        r = y - 1 / (1 + np.exp(-(t[0] * z + t[1])))
        return np.array([(r * z).mean() - 1e-3 * t[0], r.mean()])

    model.slope, model.shift = _adam(grad_scale, np.array([1.0, 0.0]), 400, 0.05)
    return model


def labelled_sample(df: DataFrame, labels: DataFrame, train=None, max_docs: int = 4000, max_bytes: int = 32 << 20, text_col: str = "text", id_col: str = "doc_id") -> tuple[list[list[bytes]], list[int]]:
    """The bounded training sample: whole texts as lines, and labels.

    Ids come first, from the labels alone (``train``: a condition on them; null ids and other labels than 0 and 1 do not count; of
    contradicting labels of an id the lower does), in hashed order, ``max_docs`` of them.  Of an id that repeats in df the first
    text counts.  Texts follow in the same order until those before have ``max_bytes`` bytes; none is cut or passed over.
    """
    known = labels.select(F.col(id_col).alias("doc_id"), F.col("quality").alias("quality")).where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull())
    known = known.groupBy("doc_id").agg(F.min("quality").cast("int").alias("quality"))
    if train is not None:
        known = known.where(train)
    ids = common.settle(known.withColumn("order", F.xxhash64(F.lit(11), "doc_id")).orderBy("order", "doc_id").limit(max_docs))
    src = df.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    rows = common.settle(src.join(F.broadcast(ids), "doc_id").groupBy("doc_id", "quality", "order").agg(F.min("text").alias("text")))
    sizes = rows.select("doc_id", "order", F.octet_length("text").alias("size")).orderBy("order", "doc_id").collect()  # max_docs rows
    before = np.concatenate(([0], np.cumsum([r["size"] for r in sizes])))[: len(sizes)]
    n = int((before < max_bytes).sum())
    got = rows.orderBy("order", "doc_id").limit(n).collect() if n else []
    return [r["text"].encode().split(b"\n") for r in got], [r["quality"] for r in got]


def train_rows(mod: int, out: set[int]):
    """Ids whose crc32 as text modulo ``mod`` is not in ``out``."""
    return ~F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(mod)).isin(*out)


def score(df: DataFrame, model: Crf, keep: tuple[str, ...] = ("doc_id",), threshold: float = 0.7, text_col: str = "text") -> DataFrame:
    """``keep`` beside score, predicted, n_lines and n_bad_lines of every whole text.

    A null or empty text is one empty line; equal texts and repeated rows get equal scores; a tie of both labels is a score
    of half the scale; an empty table gives no rows; kept columns come back under free names.
    """

    def run(column: pa.Array) -> dict[str, pa.Array]:
        docs = [t.split(b"\n") for t in common.text_bytes(column)]
        x, offsets, sizes = _layout(docs)
        good, _, _ = model.marginals(x @ model.weights, offsets)
        p = model.scale(model.documents(good, sizes, offsets))
        owner = np.repeat(np.arange(len(docs)), np.diff(offsets))
        return {
            "score": pa.array(p),
            "predicted": pa.array((p >= threshold).astype(np.int32)),
            "n_lines": pa.array(np.diff(offsets)),
            "n_bad_lines": pa.array(np.bincount(owner, good < 0.5, len(docs)).astype(np.int64)),
        }

    return common.annotate(df, run, {"score": "double", "predicted": "int", "n_lines": "long", "n_bad_lines": "long"}, list(keep), text_col)


def line_labels(df: DataFrame, model: Crf, keep: tuple[str, ...] = ("doc_id",), text_col: str = "text") -> DataFrame:
    """``keep`` and ``lines``: for each line its text, whether it is good, and the probability."""

    def run(column: pa.Array) -> dict[str, pa.Array]:
        docs = [t.split(b"\n") for t in common.text_bytes(column)]
        x, offsets, _ = _layout(docs)
        good, _, _ = model.marginals(x @ model.weights, offsets)
        flat = [line for d in docs for line in d]
        items = pa.StructArray.from_arrays([pa.array(flat, pa.binary()).cast(pa.string()), pa.array(good >= 0.5), pa.array(good)], names=["text", "good", "p"])
        return {"lines": pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), items)}

    return common.annotate(df, run, {"lines": "array<struct<text: string, good: boolean, p: double>>"}, list(keep), text_col)
