"""Toxicity by a classifier chain.

Categories are predicted in order. Each has a linear model over binary word features and the probabilities
of the categories before it; the later models are trained on out-of-fold probabilities of the earlier
ones, so they meet the same kind of input at scoring time. Features are whole words and word beginnings of
``PREFIXES`` letters, chosen by their association with each category over the training rows.

Bound of the fit: ``max_train`` labelled rows, those with the smallest hash of their id; everything
else is over all rows. Rows whose labels are null are not trained on; of several labels of one id each
category takes the greatest, and of several texts that of the least hash. Null and empty texts have no
features and get the probabilities of the intercepts. Equal texts get equal probabilities.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import textkernel as K
from .shared import free_name, plus

PREFIXES = (3, 4, 5, 6)
MAX_TRAIN = 8_000
MAX_FEATURES = 1_024
FOLDS = 5
_LETTERS = re.compile(r"[^\W\d_]+")
_MARKS = re.compile(r"[^\w\s.,;:]{2,3}| [|] ")


def features_of(text: str | None) -> set[str]:
    """Words (``=word``), word beginnings (``^abc``), runs of marks (``~***``) and forms (``~caps``, ``~again``) of a text."""
    if not text:
        return set()
    run = _LETTERS.findall(low := text.lower())
    words = set(run)
    form = {f"~{m}" for m in set(_MARKS.findall(low))}
    if 2 * sum(1 for a, b in zip(text, low) if a != b) > sum(map(len, run)):
        form.add("~caps")
    if any(a == b == c for a, b, c in zip(run, run[1:], run[2:])):
        form.add("~again")
    return {f"={w}" for w in words} | {f"^{w[:k]}" for w in words for k in PREFIXES if len(w) > k} | form


def probability(logit: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(logit, -60, 60)))


@dataclass
class Linear:
    """Logistic regression: the weights, then the intercept."""

    w: np.ndarray

    def logit(self, x: np.ndarray) -> np.ndarray:
        return x @ self.w[:-1] + self.w[-1]


def fit_linear(x: np.ndarray, y: np.ndarray, l2: float = 1.0, steps: int = 40) -> Linear:
    """Newton's method on the penalised likelihood; the intercept has no penalty. Sums are taken over blocks of rows, so no second copy of x is made."""
    d = x.shape[1] + 1
    w, ridge = np.zeros(d), np.full(d, l2)
    ridge[-1] = 1e-6
    for _ in range(steps):
        hessian, slope = np.diag(ridge), ridge * w
        for at in range(0, len(x), 512):
            a = np.hstack([x[at : at + 512].astype(np.float64), np.ones((len(x[at : at + 512]), 1))])
            p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
            hessian += (a * (p * (1 - p))[:, None]).T @ a
            slope += a.T @ (p - y[at : at + 512])
        step = np.linalg.solve(hessian, slope)
        w -= step
        if np.abs(step).max() < 1e-6:
            break
    return Linear(w)


@dataclass
class Chain:
    """A fitted chain: per category the ids of its features, its model and the cut above which it holds."""

    categories: list[str]
    vocabulary: dict[str, int]
    models: list[Linear]
    columns: list[np.ndarray]
    cuts: list[float]

    def dense(self, ids: list[list[int]]) -> np.ndarray:
        out = np.zeros((len(ids), len(self.vocabulary)), dtype=np.float32)
        for r, x in enumerate(ids):
            out[r, x] = 1
        return out

    def logits(self, x: np.ndarray) -> np.ndarray:
        """One column a category; each model is fed the probabilities of those before it."""
        found, fed = np.zeros((len(x), 0)), np.zeros((len(x), 0))
        for model, columns in zip(self.models, self.columns, strict=True):
            own = model.logit(np.hstack([x[:, columns], fed]))[:, None]
            found, fed = np.hstack([found, own]), np.hstack([fed, probability(own)])
        return found

    def ids_of(self, text: str | None) -> list[int]:
        get = self.vocabulary.get
        return [i for f in features_of(text) if (i := get(f)) is not None]


def association(df: np.ndarray, pos: np.ndarray, n: int, n_pos: int) -> np.ndarray:
    """Signed root of the likelihood-ratio statistic of a feature's presence and the category."""
    out = np.zeros(len(df))
    for a, row, col in ((pos, df, n_pos), (df - pos, df, n - n_pos), (n_pos - pos, n - df, n_pos), (n - df - n_pos + pos, n - df, n - n_pos)):
        a = a.astype(float)
        with np.errstate(divide="ignore", invalid="ignore"):
            out += np.where(a > 0, a * np.log(a * n / (np.asarray(row, float) * col)), 0.0)
    return np.sqrt(np.maximum(2 * out, 0)) * np.where(pos * n >= df * n_pos, 1, -1)


def training_rows(docs: DataFrame, labels: DataFrame, categories: list[str], id_col: str, max_train: int) -> DataFrame:
    """At most max_train rows with id, text and labels: those of the smallest hashes."""
    known = labels.where(F.col(id_col).isNotNull() & F.greatest(*[F.col(c).isNull() for c in categories], F.lit(False)).eqNullSafe(False))
    known = known.groupBy(id_col).agg(*[F.max(F.col(c).cast("int")).alias(c) for c in categories]).orderBy(F.xxhash64(id_col), id_col).limit(max_train)
    own = docs.select(id_col, "text").join(F.broadcast(known), id_col)
    first = Window.partitionBy(id_col).orderBy(F.xxhash64("text"), "text")
    n = free_name(own, "_n")
    return own.withColumn(n, F.row_number().over(first)).where(F.col(n) == 1).drop(n)


def fit_chain(docs: DataFrame, labels: DataFrame, categories: list[str], id_col: str = "doc_id", max_train: int = MAX_TRAIN, max_features: int = MAX_FEATURES, min_df: int = 3) -> Chain:
    """Fits the chain. Counts of features are made on the executors; the driver gets the best features and the rows' ids of them."""
    rows = training_rows(docs, labels, categories, id_col, max_train).persist()
    try:
        n = rows.count()
        totals = rows.agg(*[F.sum(F.col(c).cast("long")) for c in categories]).first()

        def spread(batches):
            for batch in batches:
                found = [sorted(features_of(t)) for t in batch.column("text").to_pylist()]
                off = np.concatenate(([0], np.cumsum([len(x) for x in found])))
                pick = np.repeat(np.arange(len(found)), np.diff(off))
                flat = pa.array([f for x in found for f in x], pa.string())
                yield pa.RecordBatch.from_arrays([flat, *[batch.column(c).cast(pa.int64()).take(pa.array(pick)) for c in categories]], names=["feature", *categories])

        counts = rows.mapInArrow(spread, "feature string, " + ", ".join(f"`{c}` bigint" for c in categories)).groupBy("feature").agg(F.count("*").alias("df"), *[F.sum(c).alias(c) for c in categories]).where(F.col("df") >= min_df)

        def scored(batches):
            for batch in batches:
                df = batch.column("df").to_numpy()
                each = [np.abs(association(df, batch.column(c).to_numpy(zero_copy_only=False), n, int(t or 0))) for c, t in zip(categories, totals, strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("feature"), *map(pa.array, each)], names=["feature", *categories])

        share, vocabulary, chosen = max(1, max_features // len(categories)), {}, []
        scores = counts.mapInArrow(scored, "feature string, " + ", ".join(f"`{c}` double" for c in categories)).persist()
        for c in categories:
            best = [r[0] for r in scores.where(F.col(c) > 3.3).orderBy(F.desc(c), "feature").limit(share).collect()]
            chosen.append(np.array([vocabulary.setdefault(f, len(vocabulary)) for f in best], dtype=int))
        scores.unpersist()
        shared = rows.sparkSession.sparkContext.broadcast(vocabulary)

        def known(batches):
            for batch in batches:
                get = shared.value.get
                ids = [[i for f in features_of(t) if (i := get(f)) is not None] for t in batch.column("text").to_pylist()]
                fold = batch.column("fold")
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.list_(pa.int32())), fold, *[batch.column(c).cast(pa.int64()) for c in categories]], names=["ids", "fold", *categories])

        got = rows.withColumn("fold", F.pmod(F.xxhash64("text"), F.lit(FOLDS)).cast("int"))  # copies of a text stay in one fold
        data = got.mapInArrow(known, "ids array<int>, fold int, " + ", ".join(f"`{c}` bigint" for c in categories)).toArrow()
    finally:
        rows.unpersist()
    chain = Chain(categories, vocabulary, [], chosen, [])
    x, fold = chain.dense(data.column("ids").to_pylist()), data.column("fold").to_numpy()
    earlier = np.zeros((len(x), 0))
    for k, c in enumerate(categories):
        y = data.column(c).to_numpy().astype(float)
        own = np.hstack([x[:, chosen[k]], earlier])
        out_of_fold = np.zeros(len(x))
        for f in range(FOLDS):
            if (fold == f).any() and (fold != f).any():
                out_of_fold[fold == f] = fit_linear(own[fold != f], y[fold != f]).logit(own[fold == f])
        chain.models.append(fit_linear(own, y) if len(x) else Linear(np.zeros(own.shape[1] + 1)))
        chain.cuts.append(best_cut(out_of_fold, y))
        earlier = np.hstack([earlier, probability(out_of_fold)[:, None]])
    return chain


def best_cut(logit: np.ndarray, y: np.ndarray) -> float:
    """The cut with the best F1 over out-of-fold logits, amid the gap around it; 0 without both classes."""
    if not len(y) or y.min() == y.max():
        return 0.0
    order = np.argsort(-logit, kind="stable")
    s, hit = logit[order], np.cumsum(y[order])
    f1 = 2 * hit / (np.arange(1, len(y) + 1) + y.sum())
    f1[:-1][s[:-1] == s[1:]] = -1
    k = int(np.argmax(f1))
    return float((s[k] + s[min(k + 1, len(s) - 1)]) / 2)


def score_chain(docs: DataFrame, chain: Chain, text_col: str = "text") -> DataFrame:
    """The documents with p_<category> (double) and is_<category> (boolean) of each category."""
    names = [free_name(docs, f"{kind}_{c}") for c in chain.categories for kind in ("p", "is")]
    shared = docs.sparkSession.sparkContext.broadcast(chain)

    def run(batches):
        for batch in batches:
            for part in K.slices(batch, text_col):
                ids = [shared.value.ids_of(t) for t in part.column(text_col).to_pylist()]
                added = [[], *[[] for _ in names[1:]]]
                for at in range(0, len(ids), 512):
                    logits = shared.value.logits(shared.value.dense(ids[at : at + 512]))
                    for k, cut in enumerate(shared.value.cuts):
                        added[2 * k].append(probability(logits[:, k]))
                        added[2 * k + 1].append(logits[:, k] > cut)
                yield pa.RecordBatch.from_arrays([*part.columns, *[pa.array(np.concatenate(x)) for x in added]], names=[*part.schema.names, *names])

    schema = plus(docs, dict(zip(names, ["double", "boolean"] * len(chain.categories), strict=True)))
    return docs.mapInArrow(run, schema)
