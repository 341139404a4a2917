"""A quality classifier learned from trusted positives and unlabelled texts.

The risk is the non-negative unbiased one: with class prior p, positives P and
unlabelled U, p*R+(P) + max(0, R-(U) - p*R-(P)) under the logistic loss, so that a
fit can't profit from a negative risk on U. When the bracket falls below zero a
step goes up its gradient instead. The prior is estimated from P and U alone: a
first classifier of P against U ranks both, and the least ratio of U's tail to
P's tail, with a margin for the sample's size, bounds the share of positives.
The logit is then fitted to the labelled training rows by two numbers (slope and
intercept), so that scores read as chances.

The unlabelled side is the whole corpus: its features are written down once, and the
moments, the ranker's gradients, the tails for the prior and the risk with its
gradient are sums over all of its rows, one pass each. A sample of ``start_rows``
gives the point from which those passes start. Labelled rows may be bounded, by
``most_positive`` and ``most_negative`` (the latter serve the calibration alone).

A score depends on the text only: the shares of byte values and a few figures on
words, lines and repetition. Every row is scored.

Defined results: null text is empty and gets a score like any other; rows with a
null id count as held out; labels that are null or for unknown ids are ignored;
without positives every score is 0.5; where every document has a label, the texts of
all training rows are the unlabelled side; repeated rows get equal scores; an empty
table gives an empty result; other columns pass through, one with an added
column's name as ``input_<name>``.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphdrift.llm import common

FOLDS = 5


def fold(doc_id: Column) -> Column:
    """crc32 of the id as text, modulo the number of folds."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(FOLDS))


def text_figures(text: bytes) -> list[float]:
    """Figures on words, lines and repetition."""
    words, lines = text.split(), [x for x in text.split(b"\n") if x.strip()]
    n, k = max(1, len(words)), max(1, len(lines))
    distinct = len(set(words))
    low = text.lower().split()
    top = Counter(low).most_common(1)[0][1] if low else 0
    pairs = len(set(zip(low, low[1:])))
    kinds = len(set(lines))
    ends = sum(w[-1:].isalnum() or w[-1:] >= b"\x80" for w in words)
    upper = sum(w.isupper() for w in words)
    return [
        np.log1p(len(text)) / 10,
        np.log1p(len(words)) / 10,
        len(text) / n / 10,
        distinct / n,
        distinct / n * np.log1p(n) / 5,
        top / n,
        pairs / n,
        kinds / k,
        np.log1p(k) / 5,
        n / k / 100,
        max((len(w) for w in words), default=0) ** 0.5 / 10,
        ends / n,
        upper / n,
        sum(len(w) == 1 for w in words) / n,
        float(not words),
    ]


FIGURES = len(text_figures(b""))
WIDTH = 256 + FIGURES


def features(texts: list[bytes], block: int = 1 << 22) -> np.ndarray:
    """One row of WIDTH numbers a text: square roots of byte shares, then the figures."""
    out = np.zeros((len(texts), WIDTH), np.float32)
    at = 0
    while at < len(texts):
        end, held = at, 0
        while end < len(texts) and (end == at or held + len(texts[end]) <= block):
            held += len(texts[end])
            end += 1
        if held > block:  # one long text
            for k in range(0, held, block):
                out[at, :256] += np.bincount(np.frombuffer(texts[at][k : k + block], np.uint8), minlength=256)
        else:
            sizes = [len(t) for t in texts[at:end]]
            cell = np.repeat(np.arange(end - at) * 256, sizes) + np.frombuffer(b"".join(texts[at:end]), np.uint8)
            out[at:end, :256] = np.bincount(cell, minlength=256 * (end - at)).reshape(-1, 256)
        at = end
    out[:, :256] = np.sqrt(out[:, :256] / np.maximum(1, out[:, :256].sum(axis=1, keepdims=True)))
    out[:, 256:] = [text_figures(t) for t in texts] if texts else out[:, 256:]
    return out


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


class Adam:
    def __init__(self, n: int, rate: float):
        self.m, self.v, self.t, self.rate = np.zeros(n), np.zeros(n), 0, rate

    def step(self, g: np.ndarray) -> np.ndarray:
        self.t += 1
        self.m = 0.9 * self.m + 0.1 * g
        self.v = 0.999 * self.v + 0.001 * g * g
        return self.rate * (self.m / (1 - 0.9**self.t)) / (np.sqrt(self.v / (1 - 0.999**self.t)) + 1e-8)


def fit_plain(x: np.ndarray, y: np.ndarray, steps: int, rate: float, decay: float) -> np.ndarray:
    """Logistic regression with balanced classes; the last weight is the intercept."""
    x = np.hstack([x, np.ones((len(x), 1), x.dtype)])
    weight = np.where(y, 0.5 / max(1, y.sum()), 0.5 / max(1, (~y).sum()))
    w, adam = np.zeros(x.shape[1]), Adam(x.shape[1], rate)
    for _ in range(steps):
        g = x.T @ (weight * (_sigmoid(x @ w) - y))
        w -= adam.step(g + decay * np.append(w[:-1], 0))
    return w


def estimated_prior(p_scores: np.ndarray, u_scores: np.ndarray, delta: float = 0.1) -> float:
    """Share of positives in U: the least upper bound over tails of the ratio of U's tail to P's."""
    cuts = np.quantile(p_scores, np.linspace(0, 0.98, 99))
    p_tail = 1 - np.searchsorted(np.sort(p_scores), cuts, side="left") / len(p_scores)
    u_tail = 1 - np.searchsorted(np.sort(u_scores), cuts, side="left") / len(u_scores)
    return prior_of_tails(p_tail, u_tail, len(p_scores), len(u_scores), delta)


def prior_of_tails(p_tail: np.ndarray, u_tail: np.ndarray, n_p: int, n_u: int, delta: float = 0.1) -> float:
    """The least ratio of tails, each with a margin for the numbers of rows behind it."""
    margin = np.sqrt(np.log(4 / delta) / (2 * n_u)) + np.sqrt(np.log(4 / delta) / (2 * n_p))
    best = np.argmin((u_tail + margin) / np.maximum(p_tail, 1e-9))
    return float(np.clip(u_tail[best] / max(p_tail[best], 1e-9), 0.02, 0.98))


def risk(zp: np.ndarray, zu: np.ndarray, prior: float) -> tuple[float, float]:
    """The two parts of the unbiased risk: the positives' and the negatives' (may be negative)."""
    soft = lambda z: np.logaddexp(0, z)
    return float(prior * soft(-zp).mean()), float(soft(zu).mean() - prior * soft(zp).mean())


def fit_nonnegative(p: np.ndarray, u: np.ndarray, prior: float, start: np.ndarray, steps: int, rate: float, decay: float) -> np.ndarray:
    """Minimise the non-negative risk by full-batch steps."""
    p, u = (np.hstack([x, np.ones((len(x), 1), x.dtype)]) for x in (p, u))
    w, adam = start.copy(), Adam(len(start), rate)
    for _ in range(steps):
        zp, zu = p @ w, u @ w
        negative = risk(zp, zu, prior)[1]
        g_negative = u.T @ (_sigmoid(zu) / len(zu)) - prior * (p.T @ (_sigmoid(zp) / len(zp)))
        if negative < 0:
            g = -g_negative
        else:
            g = prior * (p.T @ ((_sigmoid(zp) - 1) / len(zp))) + g_negative
        w -= adam.step(g + decay * np.append(w[:-1], 0))
    return w


@dataclass
class Model:
    """Weights in feature space, the estimated prior and the calibration."""

    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    prior: float
    slope: float = 1.0
    intercept: float = 0.0

    def logits(self, x: np.ndarray) -> np.ndarray:
        return ((x - self.mean) / self.scale) @ self.weights[:-1] + self.weights[-1]

    def score(self, x: np.ndarray) -> np.ndarray:
        return _sigmoid(self.slope * self.logits(x) + self.intercept)


def fit(positive: np.ndarray, unlabelled: np.ndarray, negative: np.ndarray, share: float | None = None, steps: int = 400, rate: float = 0.03, decay: float = 1e-3) -> Model | None:
    """The whole fit. ``negative`` and ``share`` (of positives among labelled rows) serve the calibration alone."""
    if not len(positive) or not len(unlabelled):
        return None
    both = np.vstack([positive, unlabelled])
    mean, scale = both.mean(axis=0), both.std(axis=0) + 0.02
    p, u = ((x - mean) / scale for x in (positive, unlabelled))
    half_p, half_u = np.arange(len(p)) % 2 == 0, np.arange(len(u)) % 2 == 0
    ranker = fit_plain(np.vstack([p[half_p], u[half_u]]), np.arange(half_p.sum() + half_u.sum()) < half_p.sum(), steps // 2, rate, decay)
    rank = lambda x: x @ ranker[:-1] + ranker[-1]
    prior = estimated_prior(rank(p[~half_p]), rank(u[~half_u])) if len(p) > 1 and len(u) > 1 else 0.5
    model = Model(mean, scale, fit_nonnegative(p, u, prior, ranker, steps, rate, decay), prior)
    calibrate(model, positive, negative, share)
    return model


def calibrate(model: Model, positive: np.ndarray, negative: np.ndarray, share: float | None) -> None:
    """Fit slope and intercept of the logit to the labelled rows."""
    if len(negative) >= 10:
        z = np.concatenate([model.logits(positive), model.logits(negative)])
        y = np.arange(len(z)) < len(positive)
        share = len(positive) / len(z) if share is None else share
        weight = np.where(y, share / len(positive), (1 - share) / len(negative))
        centre, spread = z.mean(), z.std() + 1e-6
        a, adam = np.array([1.0, 0.0]), Adam(2, 0.05)
        q = np.vstack([(z - centre) / spread, np.ones(len(z))])
        for _ in range(600):
            a -= adam.step(q @ (weight * (_sigmoid(a @ q) - y)) + 1e-4 * np.array([a[0], 0]))
        model.slope, model.intercept = float(max(a[0], 1e-3) / spread), float(a[1] - max(a[0], 1e-3) * centre / spread)


def _featured(rows: DataFrame) -> DataFrame:
    """key and x (features as float16 bytes) of rows (key, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = features(common.byte_list(batch.column(1))).astype(np.float16)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([r.tobytes() for r in x], pa.binary())], names=["key", "x"])

    return rows.select("key", "text").mapInArrow(common.trimmed(run), "key long, x binary")


def _matrix(cells: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(cells), np.float16).reshape(-1, WIDTH).astype(np.float64)


def _sampled(docs: DataFrame, ids: DataFrame, salt: str, most: int) -> np.ndarray:
    """Features of at most ``most`` documents of the given ids (by hash order)."""
    some = [r[0] for r in ids.where("doc_id is not null").select("doc_id").distinct().orderBy(F.xxhash64(F.lit(salt), "doc_id"), "doc_id").limit(most).collect()]
    if not some:
        return np.zeros((0, WIDTH))
    chosen = docs.sparkSession.createDataFrame(pa.table({"key": pa.array(some, pa.int64())}).to_pandas())
    rows = docs.select(F.col("doc_id").cast("long").alias("key"), common.text_of().alias("text")).join(F.broadcast(chosen), "key", "left_semi")
    return _matrix([x for _, x in sorted((r["key"], bytes(r["x"])) for r in _featured(rows).collect())])


class Corpus:
    """The unlabelled rows' features, and sums over all of them."""

    def __init__(self, featured: DataFrame):
        self.frame, self.path = common.stored(featured)

    def total(self, fn: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> np.ndarray:
        """The sum over all rows of ``fn(features, half)``; a task sends one vector, and those are summed before the driver sees any."""

        def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            acc = None
            for batch in batches:
                if batch.num_rows:
                    got = fn(_matrix(batch.column(1).to_pylist()), batch.column(0).to_numpy() & 1)
                    acc = got if acc is None else acc + got
            if acc is not None:
                yield pa.RecordBatch.from_arrays([pa.array([acc.tobytes()], pa.binary())], names=["v"])

        def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            acc = None
            for batch in batches:
                for v in batch.column(0).to_pylist():
                    acc = np.frombuffer(v) if acc is None else acc + np.frombuffer(v)
            if acc is not None:
                yield pa.RecordBatch.from_arrays([pa.array([acc.tobytes()], pa.binary())], names=["v"])

        rows = self.frame.select("key", "x").mapInArrow(common.trimmed(partial), "v binary").repartition(8).mapInArrow(common.trimmed(summed), "v binary").collect()
        return sum(np.frombuffer(bytes(r["v"])) for r in rows)

    def some(self, most: int, rows: int) -> np.ndarray:
        """A sample of about ``most`` rows' features (by hash)."""
        part = self.frame if rows <= most else self.frame.where(F.pmod(F.xxhash64("key", "x"), F.lit(1 << 30)) < int((1 << 30) * most / rows))
        return _matrix(sorted(bytes(r["x"]) for r in part.select("x").collect()))


def descend(value: Callable[[np.ndarray], tuple[float, np.ndarray, bool]], w: np.ndarray, passes: int, memory: int = 8) -> np.ndarray:
    """Quasi-Newton steps from ``w``, each ``value(w)`` (loss, gradient, allowed) being a pass over the corpus.

    A step that is not allowed or gains nothing is halved.
    """
    loss, g, _ = value(w)
    pairs: list[tuple[np.ndarray, np.ndarray]] = []
    size = 1.0
    for _ in range(passes - 1):
        d, alphas = g.copy(), []
        for s, y in reversed(pairs):
            alphas.append(s @ d / (s @ y))
            d -= alphas[-1] * y
        if pairs:
            d *= pairs[-1][0] @ pairs[-1][1] / (pairs[-1][1] @ pairs[-1][1])
        else:
            d *= 0.1 / max(1e-12, np.abs(g).max())
        for (s, y), alpha in zip(pairs, reversed(alphas)):
            d += (alpha - y @ d / (s @ y)) * s
        new = w - size * d
        new_loss, new_g, allowed = value(new)
        if not allowed or new_loss > loss:
            size /= 2
            continue
        if (new - w) @ (new_g - g) > 1e-12:
            pairs = [*pairs, (new - w, new_g - g)][-memory:]
        w, loss, g, size = new, new_loss, new_g, 1.0
    return w


def fit_corpus(positive: np.ndarray, corpus: Corpus, negative: np.ndarray, share: float | None = None, start_rows: int = 12_000, passes: int = 20, decay: float = 1e-3) -> Model | None:
    """The whole fit, with the unlabelled side's sums over all rows."""
    told = corpus.total(lambda x, half: np.concatenate([[len(x), half.sum()], x.sum(axis=0), (x * x).sum(axis=0)]))
    if not len(positive) or np.isscalar(told) or not told[0]:
        return None
    n, odd = int(told[0]), int(told[1])
    first = fit(positive, corpus.some(start_rows, n), negative, share)
    both = len(positive) + n
    mean = (positive.sum(axis=0) + told[2 : 2 + WIDTH]) / both
    scale = np.sqrt(np.maximum(0, ((positive**2).sum(axis=0) + told[2 + WIDTH :]) / both - mean**2)) + 0.02
    # the sample's weights, in the corpus's scale
    start = np.append(first.weights[:-1] * scale / first.scale, first.weights[-1] + ((mean - first.mean) / first.scale) @ first.weights[:-1])
    widen = lambda x: np.hstack([(x - mean) / scale, np.ones((len(x), 1))])
    p = widen(positive)
    half = np.arange(len(p)) % 2 == 0
    flat = lambda w: np.append(w[:-1], 0)

    def against(w: np.ndarray) -> tuple[float, np.ndarray, bool]:
        """Balanced logistic loss of half of P against half of U."""
        sums = corpus.total(lambda x, odd: (lambda z, x: np.concatenate([[np.logaddexp(0, z).sum()], x.T @ _sigmoid(z)]))((xs := widen(x[odd == 0])) @ w, xs))
        z, m = p[half] @ w, max(1, n - odd)
        loss = (np.logaddexp(0, -z).mean() + sums[0] / m) / 2 + decay / 2 * (w[:-1] @ w[:-1])
        return loss, (p[half].T @ (_sigmoid(z) - 1) / len(z) + sums[1:] / m) / 2 + decay * flat(w), True

    prior = 0.5
    if len(p) > 1 and odd and n > odd:
        ranker = descend(against, start, max(2, passes // 2), 4)
        z = p[~half] @ ranker
        cuts = np.quantile(z, np.linspace(0, 0.98, 99))
        tails = corpus.total(lambda x, odd: (lambda s: len(s) - np.searchsorted(s, cuts, side="left"))(np.sort(widen(x[odd == 1]) @ ranker)).astype(np.float64))
        prior = prior_of_tails(1 - np.searchsorted(np.sort(z), cuts, side="left") / len(z), tails / odd, len(z), odd)

    def whole(w: np.ndarray) -> tuple[float, np.ndarray, bool]:
        """The non-negative risk; a step that makes the bracket negative is not allowed."""
        sums = corpus.total(lambda x, _: (lambda z, x: np.concatenate([[np.logaddexp(0, z).sum()], x.T @ _sigmoid(z)]))((xs := widen(x)) @ w, xs))
        z = p @ w
        bracket = sums[0] / n - prior * np.logaddexp(0, z).mean()
        g = prior * (p.T @ (_sigmoid(z) - 1) / len(z)) + sums[1:] / n - prior * (p.T @ _sigmoid(z) / len(z))
        return prior * np.logaddexp(0, -z).mean() + max(0.0, bracket) + decay / 2 * (w[:-1] @ w[:-1]), g + decay * flat(w), bracket >= 0

    model = Model(mean, scale, descend(whole, start, passes), prior)
    calibrate(model, positive, negative, share)
    return model


def unlabelled(train: DataFrame, labels: DataFrame) -> DataFrame:
    """key and x of the rows (key, text) without a label, or of all where every one has a label.

    Texts become features before rows are told apart, so that what travels is features of
    one size, not texts; the join is the same one at any size of the labels.
    """
    known = labels.select(F.col("doc_id").cast("long").alias("key")).hint("merge")
    some = train.select("key").join(known, "key", "left_anti").limit(1).count()
    return _featured(train).join(known, "key", "left_anti") if some else _featured(train)


def learn(docs: DataFrame, labels: DataFrame, label: str = "quality", most_positive: int = 6000, most_negative: int = 4000, **kw) -> Model | None:
    """Fit on training folds: their labelled positives, and all their documents without a label."""
    common.tune(docs.sparkSession)
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).where((fold(F.col("doc_id")) != 0) & F.col("y").isNotNull())
    counts = {r["y"]: r["n"] for r in known.groupBy("y").agg(F.count(F.lit(1)).alias("n")).collect()}
    positive = _sampled(docs, known.where("y = 1"), "positive", most_positive)
    if not len(positive):
        return None
    negative = _sampled(docs, known.where("y = 0"), "negative", most_negative)
    train = docs.select(F.col("doc_id").cast("long").alias("key"), common.text_of().alias("text")).where(fold(F.col("doc_id").cast("long")) != 0)
    corpus = Corpus(unlabelled(train, labels).withColumn("key", F.xxhash64("key")))
    total = counts.get(1, 0) + counts.get(0, 0)
    model = fit_corpus(positive, corpus, negative, counts.get(1, 0) / total if total else None, **kw)
    common.delete(docs.sparkSession, corpus.path)
    return model


def score_documents(docs: DataFrame, model: Model | None, threshold: float = 0.3, keep: list[str] | None = None) -> DataFrame:
    """Kept columns of ``docs`` with held_out, score and predicted."""
    common.tune(docs.sparkSession)
    keep = docs.columns if keep is None else keep
    held = (fold(F.col("doc_id")) == 0) if "doc_id" in docs.columns else F.lit(True)
    frame = common.packed(docs, keep, held_out=held, text=common.text_of())
    schema = T.StructType([frame.schema["kept"], frame.schema["held_out"], T.StructField("score", T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = common.byte_list(batch.column(2))
            score = model.score(features(texts).astype(np.float64)) if model else np.full(len(texts), 0.5)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.round(score, 9))], names=schema.names)

    out = frame.mapInArrow(common.trimmed(run), schema)
    return common.unpacked(out, keep, held_out=F.col("held_out"), score=F.col("score"), predicted=(F.col("score") >= threshold).cast("int"))


def quality_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""
    return score_documents(docs, learn(docs, labels), keep=["doc_id"])
