"""Accuracy measures: classification scores, exactness of walks, error of the approximation."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.evaluation import BinaryClassificationEvaluator
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .config import WalkParams, written
from .walk.bounds import bound_high, bound_low
from .walk.pairs import transition_rows
from .walk.rng import SPAN, draw48


def f1(pred: DataFrame, truth: DataFrame, average: str = "micro") -> DataFrame:
    """One row (f1) from (vid, label) rows; a vertex may have several labels.  Labels without truth and prediction do not count."""
    p, t = pred.select("vid", "label").distinct().withColumn("p", F.lit(1)), truth.select("vid", "label").distinct().withColumn("t", F.lit(1))
    both = p.join(t, ["vid", "label"], "full")
    hit, wrong, missed = F.sum((F.col("p").isNotNull() & F.col("t").isNotNull()).cast("long")), F.sum(F.col("t").isNull().cast("long")), F.sum(F.col("p").isNull().cast("long"))
    per = both.groupBy("label").agg(hit.alias("tp"), wrong.alias("fp"), missed.alias("fn"))
    if average == "macro":
        return per.agg(F.avg(2 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn"))).alias("f1"))
    return per.agg((2 * F.sum("tp") / (2 * F.sum("tp") + F.sum("fp") + F.sum("fn"))).alias("f1"))


def labelled_split(labels: DataFrame, fraction: float, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """(training, test) rows of vertices, by a counter-based draw."""
    place = draw48(seed, 0, "vid", 0) / float(SPAN)
    return labels.where(place < fraction), labels.where(place >= fraction)


def linear_scores(coefficients, intercepts, of: str = "features"):
    """A column of one linear score per row of ``coefficients``, from an array column; plain expressions, so no fitted model is shipped to tasks."""
    dot = lambda row, b: F.aggregate(F.zip_with(F.col(of).cast("array<double>"), F.array(*map(F.lit, row)), lambda x, c: x * c), F.lit(float(b)), lambda s, x: s + x)
    return F.array(*[dot([float(c) for c in row], b) for row, b in zip(coefficients, intercepts, strict=True)])


def fit_labels(train: DataFrame, names: list[int], ridge: float = 1e-3, max_iter: int = 30, tolerance: float = 1e-6) -> tuple[np.ndarray, np.ndarray]:
    """(coefficients, intercepts) of one logistic regression per label, all fitted together by Newton steps.

    ``train``: (features array<double>, labels array<int>).  The penalty is on coefficients of features scaled to unit deviation,
    beside the mean loss.  A step is one pass: tasks send gradients and curvatures of all labels, the driver holds nothing else.
    """
    n, sums, squares = train.select(F.lit(1).alias("n"), F.posexplode("features")).groupBy("pos").agg(F.count("*").alias("n"), F.avg("col").alias("m"), F.stddev_samp("col").alias("s")).orderBy("pos").toArrow().select(["n", "m", "s"]).columns
    if not len(n) or not len(names):
        return np.zeros((len(names), len(n))), np.zeros(len(names))
    rows, middle, spread = n[0].as_py(), np.asarray(sums, float), np.nan_to_num(np.asarray(squares, float))
    scale = np.where(spread > 0, 1 / np.where(spread > 0, spread, 1), 0.0)
    width, order = len(n) + 1, np.asarray(names)
    penalty = np.append(np.full(width - 1, ridge), 0.0)

    def passed(beta: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        def part(batches):
            loss, slope, curve = np.zeros(len(order)), np.zeros((len(order), width)), np.zeros((len(order), width, width))
            for b in batches:
                x = np.asarray(b.column("features").flatten(), float).reshape(b.num_rows, width - 1)
                x = np.hstack([(x - middle) * scale, np.ones((b.num_rows, 1))])
                held = b.column("labels")
                owner = np.repeat(np.arange(b.num_rows), np.asarray(held.value_lengths()))
                y = np.zeros((b.num_rows, len(order)))
                at = np.searchsorted(order, np.asarray(held.flatten()))
                y[owner, at] = 1
                z = x @ beta.T
                chance = 1 / (1 + np.exp(-np.clip(z, -500, 500)))
                loss += (np.logaddexp(0, z) - y * z).sum(0)
                slope += (chance - y).T @ x
                for k in range(len(order)):
                    curve[k] += (x * (chance[:, k] * (1 - chance[:, k]))[:, None]).T @ x
            yield pa.RecordBatch.from_arrays([pa.array([v.ravel().tolist()], pa.list_(pa.float64())) for v in (loss, slope, curve)], ["loss", "slope", "curve"])

        found = train.select("features", "labels").mapInArrow(part, "loss array<double>, slope array<double>, curve array<double>").toArrow()
        loss, slope, curve = (np.sum([np.asarray(v.values) for v in found.column(c)], axis=0) / rows for c in ("loss", "slope", "curve"))
        loss = loss + 0.5 * (beta * beta * penalty).sum(1)
        return loss, slope.reshape(beta.shape) + beta * penalty, curve.reshape(len(order), width, width) + np.diag(np.append(penalty[:-1], 1e-12))

    beta = np.zeros((len(order), width))
    loss, slope, curve = passed(beta)
    for _ in range(max_iter):
        move = np.stack([np.linalg.lstsq(c, g, rcond=None)[0] for c, g in zip(curve, slope, strict=True)])
        if np.abs(move).max() < tolerance:
            break
        factor = np.ones(len(order))
        while True:  # a label whose loss would grow takes half the step
            tried = beta - factor[:, None] * move
            told = passed(tried)
            worse = (told[0] > loss + 1e-12) & (factor > 1e-4)
            if not worse.any():
                break
            factor[worse] /= 2
        beta, (loss, slope, curve) = tried, told
    coefficients = beta[:, :-1] * scale
    return coefficients, beta[:, -1] - coefficients @ middle


def classify(vectors: DataFrame, labels: DataFrame, fraction: float, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """(predicted, true) label rows of the test vertices: one logistic regression per label, as many top labels as a vertex has.

    ``labels``: (vid, labels array<int>).
    """
    rows = written(vectors.join(labels, "vid").select("vid", F.col("vec").cast("array<double>").alias("features"), "labels"), "labelled")
    train, test = labelled_split(rows, fraction, seed)
    train = train.persist()
    try:
        names = [r[0] for r in train.select(F.explode("labels")).distinct().orderBy("col").collect()]
        fitted = fit_labels(train, names)
    finally:
        train.unpersist()
    pairs = F.arrays_zip(linear_scores(*fitted).alias("p"), F.array(*map(F.lit, names)).cast("array<int>").alias("label"))
    top = F.slice(F.reverse(F.array_sort(pairs)), 1, F.size("labels"))
    scored = written(test.select("vid", "labels", F.transform(top, lambda t: t["label"]).alias("found")), "scored")
    return scored.select("vid", F.explode("found").alias("label")), scored.select("vid", F.explode("labels").alias("label"))


def link_auc(features: DataFrame, seed: int = 42) -> float:
    """Area under the curve of a logistic regression on pair features (a, b, features, label), half of the pairs for training."""
    rows = features.select("a", "b", F.col("features").cast("array<double>").alias("features"), F.col("label").cast("double").alias("label"))
    half = draw48(seed, "a", "b", 0) < SPAN // 2
    model = LogisticRegression(maxIter=30).fit(rows.where(half).select(array_to_vector("features").alias("features"), "label"))
    scored = rows.where(~half).select("label", linear_scores([model.coefficients.toArray()], [model.intercept])[0].alias("rawPrediction"))
    return BinaryClassificationEvaluator().evaluate(scored)


def observed_moves(steps: DataFrame) -> DataFrame:
    """(u, v, x, n): how often walks that came from u to v went on to x."""
    by = Window.partitionBy("start", "round").orderBy("step")
    rows = steps.select(F.lag("vertex", 2).over(by).alias("u"), F.lag("vertex").over(by).alias("v"), F.col("vertex").alias("x"))
    return rows.where("u IS NOT NULL").groupBy("u", "v", "x").agg(F.count("*").alias("n"))


def walk_distance(steps: DataFrame, edges: DataFrame, params: WalkParams) -> DataFrame:
    """(u, v, n, tv, chi_square): distance of observed moves from exact probabilities, per pair that was visited."""
    seen = observed_moves(steps)
    met = seen.groupBy("u", "v").agg(F.array_sort(F.collect_list(F.struct("x", "n"))).alias("m"))
    rows = transition_rows(edges, params, met.select("u", "v", F.col("m.x").alias("xs"), F.col("m.n").alias("ns"))).withColumn("prob", F.col("pi") / F.col("total"))
    want = F.col("prob") * F.col("visits")
    return rows.groupBy("u", "v").agg(F.first("visits").alias("n"), (0.5 * F.sum(F.abs(F.col("n") / F.col("visits") - F.col("prob")))).alias("tv"), F.sum((F.col("n") - want) * (F.col("n") - want) / want).alias("chi_square"))


def approx_pairs(edges: DataFrame, popular: DataFrame, params: WalkParams, eps: float) -> DataFrame:
    """(u, v, low, high) of moves from an unpopular u to a popular v whose bounds lie closer than ``eps``."""
    d = edges.groupBy("src").agg(F.count("*").alias("deg"), F.min("w").alias("wmin"), F.max("w").alias("wmax"))
    uv = edges.select(F.col("src").alias("u"), F.col("dst").alias("v"))
    uv = uv.join(popular.select(F.col("vid").alias("v")), "v", "left_semi").join(popular.select(F.col("vid").alias("u")), "u", "left_anti")
    uv = uv.join(d.select(F.col("src").alias("u"), F.col("deg").alias("du")), "u").join(d.select(F.col("src").alias("v"), F.col("deg").alias("dv"), "wmin", "wmax"), "v")
    args = ("du", "dv", "wmin", "wmax")
    low, high = (f(*(F.col(a) for a in args), params.p, params.q) for f in (bound_low, bound_high))
    return uv.select("u", "v", low.alias("low"), high.alias("high")).where(F.col("high") - F.col("low") < eps)


def approx_error(edges: DataFrame, popular: DataFrame, params: WalkParams, eps: float) -> DataFrame:
    """(u, v, max_error, max_allowed, return_error, tv) at approximated pairs: static against exact probabilities.

    The bounds speak of x other than u, so the return vertex has a column of its own; tv is half the sum of all errors.
    """
    pairs = approx_pairs(edges, popular, params, eps)
    pairs = written(pairs, "approx-pairs")
    rows = transition_rows(edges, params, pairs.select("u", "v")).select("u", "v", "x", (F.col("pi") / F.col("total")).alias("prob"), (F.col("w") / F.col("wsum")).alias("static"))
    error = F.abs(F.col("static") - F.col("prob"))
    other = F.col("x") != F.col("u")
    per = rows.groupBy("u", "v").agg(F.max(F.when(other, error)).alias("max_error"), F.min(F.when(other, F.col("static"))).alias("least"), F.max(F.when(other, F.col("static"))).alias("most"), F.max(F.when(~other, error)).alias("return_error"), (0.5 * F.sum(error)).alias("tv"))
    allowed = F.greatest(F.col("high") - F.col("least"), F.col("most") - F.col("low"))
    return per.join(pairs, ["u", "v"]).select("u", "v", "max_error", allowed.alias("max_allowed"), "return_error", "tv")


def stationary_gap(steps: DataFrame, edges: DataFrame, after: int = 10) -> DataFrame:
    """One row (tv): visits after some moves against shares of weighted degree; small for long unbiased walks."""
    share = edges.groupBy(F.col("src").alias("vid")).agg(F.sum("w").alias("ws"))
    visits = steps.where(F.col("step") > after).groupBy(F.col("vertex").alias("vid")).agg(F.count("*").alias("n"))
    rows = share.join(visits, "vid", "left").fillna(0, ["n"])
    sums = rows.agg(F.sum("n").alias("sn"), F.sum("ws").alias("sw"))
    return rows.join(F.broadcast(sums)).agg((0.5 * F.sum(F.abs(F.col("n") / F.col("sn") - F.col("ws") / F.col("sw")))).alias("tv"))


__all__ = ["approx_error", "approx_pairs", "classify", "f1", "labelled_split", "link_auc", "observed_moves", "stationary_gap", "walk_distance"]
