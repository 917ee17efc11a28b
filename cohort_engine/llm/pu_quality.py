"""Quality classifier by positive-unlabelled learning.

Texts labelled good are trusted positives; all texts stand for unlabelled web text. Texts labelled bad are not used at all. A small network is
trained on the non-negative unbiased risk: the positive part counts with the class prior, the negative part is estimated
from unlabelled texts less what positives among them add, and is kept from falling below zero.

Training starts on bounded samples (``Sizes``) and goes on with one pass over all texts: every task takes steps of the same risk over its own rows,
with the sampled positives beside them, and the tasks' weights are averaged by their rows. The class prior is estimated without
negatives, from where the positives' scores are densest relative to those of all texts. Means, scales, prior and calibration are
counted over all texts (in bins of the score, of which there are few). The calibration fits the score to the share of good texts
in each bin, which the prior and the two densities give.

Features come from the text alone: frequencies of pairs of character classes, and a few measures of length
and repetition; they are kept as half-precision numbers in the shared folder, a quarter of a usual text's size.

Defined results: null and empty texts are scored like a text without characters; rows with a null id are never
held out and never sampled; of several labels of an id the largest counts; a table without labelled positives
gives 0.5 everywhere; repeated rows get equal scores; empty tables give empty ones; other columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow_schema, cut, map_columns, slices

_CLASSES = 16
_OF = np.full(256, 13, np.int64)
for _k, _chars in enumerate((" \t", "\n\r", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", ".", ",", "!", "?", ";:", "\"'", "()[]{}", "|")):
    _OF[[ord(c) for c in _chars]] = _k
_OF[ord("-")] = 14
_OF[128:] = 15
WIDTH = _CLASSES * _CLASSES + 8


def features(text: str | None) -> np.ndarray:
    raw = (text or "").encode("utf-8", "surrogatepass")
    out = np.zeros(WIDTH, np.float32)
    if raw:
        kinds = _OF[np.frombuffer(raw, np.uint8)]
        pairs = np.bincount(kinds[:-1] * _CLASSES + kinds[1:], minlength=_CLASSES * _CLASSES)
        out[:-8] = np.sqrt(pairs / len(raw))
    words, lines = raw.split(), [x for x in raw.split(b"\n") if x.strip()]
    n = len(words)
    threes = set(zip(words, words[1:], words[2:], strict=False))
    out[-8:] = (
        math.log1p(n) / 8,
        n / 10 if n < 10 else 1,
        len(set(words)) / n if n else 1,
        len(threes) / (n - 2) if n > 2 else 1,
        len(set(lines)) / len(lines) if lines else 1,
        math.log1p(len(raw) / max(1, len(lines))) / 8,
        min(len(raw) / max(1, n), 20) / 20,
        sum(x.rstrip()[-1:] in b".!?:;\"" for x in lines) / len(lines) if lines else 0,
    )
    return out


@dataclass(frozen=True)
class Sizes:
    """Most labelled texts that are learnt from, and most texts on which training starts before all are passed over."""

    positive: int = 8000
    unlabelled: int = 12000


def remainder(id_col: Column) -> Column:
    return F.crc32(id_col.cast("string")) % 3


@dataclass
class PuModel:
    prior: float
    layers: tuple[np.ndarray, ...] | None
    mean: np.ndarray | None = None
    scale: np.ndarray | None = None
    slope: float = 1.0
    shift: float = 0.0

    def margin(self, x: np.ndarray) -> np.ndarray:
        if self.layers is None:
            return np.zeros(len(x))
        a, b, c, d = self.layers
        return np.tanh((x - self.mean) / self.scale @ a + b) @ c + d

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * self.margin(x) + self.shift, -30, 30)))


BINS, SPAN = 2000, 40.0
#: The prior is read off where at least this share of positives scores as high.
LEAST_TAIL = 0.2


def bin_of(margin: np.ndarray) -> np.ndarray:
    return np.clip(((margin + SPAN / 2) / SPAN * BINS).astype(np.int64), 0, BINS - 1)


def prior_from_bins(positive: np.ndarray, unlabelled: np.ndarray) -> float:
    """The share of positives among unlabelled texts, from counts by bin of the score: above any score the unlabelled hold at least the prior's
    share of what the positives hold, and next to nothing more where the score tells them best from others. A margin for chance keeps
    small tails from being taken for that."""
    p, u = positive[::-1].cumsum() / positive.sum(), unlabelled[::-1].cumsum() / unlabelled.sum()
    spread = np.sqrt(np.maximum(u, 1 / unlabelled.sum()) / unlabelled.sum()) + np.sqrt(np.maximum(p, 1 / positive.sum()) / positive.sum())
    wide = p >= LEAST_TAIL
    return float(np.clip(((u + spread) / np.maximum(p, 1e-9))[wide].min(), 0.02, 0.98))


def calibration(positive: np.ndarray, unlabelled: np.ndarray, prior: float) -> tuple[float, float]:
    """``slope, shift`` of the logistic score: fitted to the share of good texts in each bin, by the counts of unlabelled texts."""
    middle = (np.arange(BINS) + 0.5) / BINS * SPAN - SPAN / 2
    # runs of bins that hold a fair number of both kinds
    cells = np.floor((positive + unlabelled).cumsum() / max(1.0, (positive + unlabelled).sum() / 60)).astype(int)
    p, u = np.bincount(cells, positive) / positive.sum(), np.bincount(cells, unlabelled) / unlabelled.sum()
    at = np.bincount(cells, unlabelled * middle) / np.maximum(np.bincount(cells, unlabelled), 1e-9)
    on = u > 0
    share, weight, x = np.clip(prior * p[on] / u[on], 0, 1), u[on], at[on]
    z, theta = np.stack([x, np.ones(len(x))], 1), np.array([1.0, 0.0])
    for _ in range(100):
        q = 1 / (1 + np.exp(-np.clip(z @ theta, -30, 30)))
        bend = (z * (weight * q * (1 - q))[:, None]).T @ z + 1e-3 * np.eye(2)
        step = np.linalg.solve(bend, z.T @ (weight * (q - share)) + 1e-4 * (theta - [1, 0]))
        theta = theta - np.clip(step, -1, 1)
        if np.abs(step).max() < 1e-9:
            break
    return (float(theta[0]), float(theta[1])) if theta[0] > 0 else (1.0, 0.0)


def risk(layers: list[np.ndarray], p: np.ndarray, u: np.ndarray, prior: float) -> tuple[float, float, list[np.ndarray]]:
    """The positive part of the risk, the negative part (which may be below zero), and the gradient of the step to take: that of the whole risk, or,
    where the negative part is below zero, that which leads back from overfitting."""
    x = np.concatenate([p, u])
    h = np.tanh(x @ layers[0] + layers[1])
    z = h @ layers[2] + layers[3]
    good = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
    zp, zu = good[: len(p)], good[len(p) :]
    # loss of calling z positive: 1 - sigmoid(z); negative: sigmoid(z)
    positive_part, negative_part = prior * (1 - zp.mean()), zu.mean() - prior * zp.mean()
    dp, du = zp * (1 - zp) / len(p), zu * (1 - zu) / len(u)
    grad = np.concatenate([-2 * prior * dp, du]) if negative_part >= 0 else np.concatenate([prior * dp, -du])
    back = grad[:, None] * layers[2] * (1 - h * h)
    return float(positive_part), float(negative_part), [x.T @ back, back.sum(0), h.T @ grad, grad.sum()]


class _Steps:
    """Adam steps with a little decay of the two weight matrices."""

    def __init__(self, layers: list[np.ndarray], rate: float) -> None:
        self.layers, self.rate, self.t = layers, rate, 0
        self.first, self.second = [np.zeros_like(w) for w in layers], [np.zeros_like(w) for w in layers]

    def take(self, slopes: list[np.ndarray]) -> None:
        self.t += 1
        for k, g in enumerate(slopes):
            if k in (0, 2):
                g = g + 1e-4 * self.layers[k]
            self.first[k] = 0.9 * self.first[k] + 0.1 * g
            self.second[k] = 0.999 * self.second[k] + 0.001 * g * g
            self.layers[k] = self.layers[k] - self.rate * (self.first[k] / (1 - 0.9**self.t)) / (np.sqrt(self.second[k] / (1 - 0.999**self.t)) + 1e-8)


def fit_risk(positive: np.ndarray, unlabelled: np.ndarray, prior: float, hidden: int = 16, epochs: int = 30, batch: int = 500, rate: float = 0.005, seed: int = 7) -> list[np.ndarray]:
    """Layers trained on scaled features of bounded samples."""
    rng = np.random.default_rng(seed)
    width = positive.shape[1]
    steps = _Steps([rng.normal(0, 1 / math.sqrt(width), (width, hidden)), np.zeros(hidden), rng.normal(0, 1 / math.sqrt(hidden), hidden), np.zeros(())], rate)
    rounds = max(1, math.ceil(len(unlabelled) / batch))
    for _ in range(epochs):
        pu, pp = rng.permutation(len(unlabelled)), rng.permutation(len(positive))
        for s in range(rounds):
            steps.take(risk(steps.layers, positive[pp[s % len(positive) :: rounds]], unlabelled[pu[s::rounds]], prior)[2])
    return steps.layers


def _flat(layers: list[np.ndarray]) -> np.ndarray:
    return np.concatenate([np.ravel(w) for w in layers])


def _shaped(flat: np.ndarray, like: list[np.ndarray]) -> list[np.ndarray]:
    ends = np.cumsum([w.size for w in like])
    return [flat[e - w.size : e].reshape(w.shape) for w, e in zip(like, ends, strict=True)]


def _read(column: pa.Array) -> np.ndarray:
    """The features of a batch."""
    return np.frombuffer(b"".join(column.to_pylist()), np.float16).reshape(-1, WIDTH).astype(np.float64)


def _over(df: DataFrame, fn, schema: str) -> DataFrame:
    """``fn`` from the batches of a partition, as features, to the rows of its result."""
    kinds = arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for columns in fn((b, _read(b.column(b.schema.get_field_index("x")))) for b in slices(batches)):
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, kinds, strict=True)], schema=kinds)

    return df.mapInArrow(run, schema)


def featured(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, held_out, x`` of every document, written to the shared folder."""

    def run(c: dict[str, list]) -> dict[str, list]:
        return {"id": c["id"], "held_out": c["held_out"], "x": [features(t).astype(np.float16).tobytes() for t in c["text"]]}

    narrow = docs.select(F.col(id_col).cast("bigint").alias("id"), F.coalesce(remainder(F.col(id_col)) == 1, F.lit(False)).alias("held_out"), F.col(text_col).alias("text"))
    return cut(map_columns(narrow, run, "id bigint, held_out boolean, x binary"))


def _moments(table: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Mean and scale of each feature over all documents."""

    def run(batches):
        n, one, two = 0, np.zeros(WIDTH), np.zeros(WIDTH)
        for _, x in batches:
            n, one, two = n + len(x), one + x.sum(0), two + (x * x).sum(0)
        if n:
            yield np.arange(WIDTH), np.full(WIDTH, n), one, two

    rows = _over(table.select("x"), run, "k int, n bigint, one double, two double").groupBy("k").agg(*(F.sum(c).alias(c) for c in ("n", "one", "two"))).orderBy("k").toPandas()  # a row for each feature
    mean = rows["one"].to_numpy() / rows["n"].to_numpy()
    return mean, np.sqrt(np.maximum(rows["two"].to_numpy() / rows["n"].to_numpy() - mean**2, 0)) + 0.02


def _bins(table: DataFrame, good: DataFrame, model: PuModel) -> tuple[np.ndarray, np.ndarray]:
    """How many labelled good texts, and how many texts at all, score in each bin."""
    shared = table.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b, x in batches:
            yield b.column(0), bin_of(shared.value.margin(x))

    scored = cut(_over(table.select("id", "x"), run, "id bigint, bin int"))
    out = []
    for rows in (scored.join(good, "id", "left_semi"), scored):
        counts = np.zeros(BINS)
        for r in rows.groupBy("bin").count().collect():  # at most BINS rows
            counts[r["bin"]] = r["count"]
        out.append(counts)
    return out[0], out[1]


def _passed_over(table: DataFrame, model: PuModel, positive: np.ndarray, batch: int = 500, rate: float = 0.001) -> list[np.ndarray]:
    """The layers after one pass over all texts: tasks take steps over their own rows, and their weights are averaged."""
    shared = table.sparkSession.sparkContext.broadcast((model, positive))
    like = list(model.layers)

    def run(batches):
        start, good = shared.value
        steps = _Steps([np.array(w) for w in start.layers], rate)
        rows, at = 0, 0
        for _, x in batches:
            x = (x - start.mean) / start.scale
            for k in range(0, len(x), batch):
                u = x[k : k + batch]
                p = good.take(np.arange(at, at + min(batch, len(good))), axis=0, mode="wrap")
                at += len(p)
                # a short batch of unlabelled texts counts by its size
                steps.take([g * len(u) / batch for g in risk(steps.layers, p, u, start.prior)[2]])
                rows += len(u)
        if rows:
            flat = _flat(steps.layers)
            yield np.arange(len(flat)), flat * rows, np.full(len(flat), rows)

    sums = _over(table.select("x"), run, "k int, w double, n bigint").groupBy("k").agg(F.sum("w").alias("w"), F.sum("n").alias("n")).orderBy("k").toPandas()  # a row for each weight
    return _shaped(sums["w"].to_numpy() / sums["n"].to_numpy(), like)


def train(table: DataFrame, labels: DataFrame, id_col: str = "doc_id", label_col: str = "quality", sizes: Sizes = Sizes()) -> PuModel:
    """A model from the table that :func:`featured` makes and the labels of texts that aren't held out."""
    known = labels.select(F.col(id_col).cast("bigint").alias("id"), F.col(label_col).cast("int").alias("label"))
    known = known.where(F.col("label").isin(0, 1) & F.col("id").isNotNull() & (remainder(F.col("id")) != 1)).groupBy("id").agg(F.max("label").alias("label"))
    good = cut(known.where("label = 1").select("id"))
    order = F.xxhash64("id")
    picked = good.orderBy(order, "id").limit(sizes.positive).select("id", F.lit("p").alias("kind"))
    picked = picked.unionByName(table.where("id is not null").select("id").orderBy(order, "id").limit(sizes.unlabelled).distinct().select("id", F.lit("u").alias("kind")))  # bounded by Sizes
    found = table.join(F.broadcast(picked), "id").groupBy("id", "kind").agg(F.min("x").alias("x")).orderBy("kind", "id").toArrow()  # one row for each id picked
    kind = np.array(found.column("kind").to_pylist(), dtype="U1")
    x = np.frombuffer(b"".join(found.column("x").to_pylist()), np.float16).reshape(-1, WIDTH).astype(np.float64)
    if not (kind == "p").any():
        return PuModel(0.5, None)
    mean, scale = _moments(table)
    x = (x - mean) / scale
    p, u = x[kind == "p"], x[kind == "u"]
    model = PuModel(0.5, tuple(fit_risk(p, u, 0.5)), mean, scale)
    prior = prior_from_bins(*_bins(table, good, model))
    model = PuModel(prior, tuple(fit_risk(p, u, prior)), mean, scale)
    model.layers = tuple(_passed_over(table, model, p))
    positive, every = _bins(table, good, model)
    model.prior = prior_from_bins(positive, every)
    model.slope, model.shift = calibration(positive, every, model.prior)
    return model


def classify(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", sizes: Sizes = Sizes()) -> DataFrame:
    """A row for each document: ``id_col, held_out, score, predicted``."""
    table = featured(docs, id_col, text_col)
    shared = docs.sparkSession.sparkContext.broadcast(train(table, labels, id_col, label_col, sizes))

    def run(batches):
        for b, x in batches:
            score = shared.value.score(x)
            yield b.column(0), b.column(1), score, (score >= 0.5).astype(np.int32)

    return _over(table, run, "id bigint, held_out boolean, score double, predicted int").withColumnRenamed("id", id_col)
