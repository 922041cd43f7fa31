"""Learning tasks on the map-reduce-update model."""

from __future__ import annotations

import math

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.losses import value_and_slope
from ..operators.mru import MRU, run_mru
from ..plans.cost import choose_layout
from ..runtime import RunReport, version


def bgd(train: DataFrame, features: list[str], loss: str = "squared", eta: float = 0.5, l2: float = 0.0, iterations: int = 5, topology: str = "early", cache: bool = False, decay: float = 0.0, intercept: bool = True, label: str = "y") -> tuple[list[float], RunReport, list[list[float]]]:
    """Batch gradient descent of a linear model over feature columns: (weights, report, weights by round).

    w starts at 0; the gradient is the mean over records; w <- w - eta_j (g / n + l2 w), with eta_j = eta / (1 + decay j) and the first feature (the
    intercept) not regularised. The loss of round j is measured on the model before its update."""
    y = F.col(label).cast("double")

    def stats(w):
        p = sum((F.lit(float(v)) * F.col(f) for v, f in zip(w[1:], features[1:])), F.lit(float(w[0])) * F.col(features[0]))
        value, slope = value_and_slope(loss, p, y)
        return {f"g{k}": slope * F.col(f) for k, f in enumerate(features)} | {"loss": value, "n": F.lit(1).cast("long")}

    def update(j, w, s):
        n = s["n"] or 0
        if not n:
            return w
        step = eta / (1 + decay * j)
        return [v - step * (s[f"g{k}"] / n + (0.0 if intercept and k == 0 else l2 * v)) for k, v in enumerate(w)]

    model, report, models = run_mru(MRU(lambda: [0.0] * len(features), stats, update), train, iterations, topology, cache)
    n = train.count()
    report.loss = [x / n for x in report.loss if x is not None] if n else []
    return model, report, models


def bgd_dense_arrays(train: DataFrame, dim: int, loss: str = "hinge", eta: float = 0.5, iterations: int = 5, x: str = "x", label: str = "y") -> tuple[list[float], RunReport, list]:
    """The same over an array column: the model is one literal array, the gradient is summed component-wise in one row a task."""
    y = F.col(label).cast("double")

    def stats(w):
        p = F.aggregate(F.zip_with(F.col(x), F.array(*[F.lit(float(v)) for v in w]), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
        value, slope = value_and_slope(loss, F.col("__p"), y)
        return p, value, slope

    w, report = [0.0] * dim, RunReport()
    models = [w]
    for _ in range(iterations):
        p, value, slope = stats(w)
        rows = train.withColumn("__p", p).select(slope.alias("d"), value.alias("l"), x)
        s = rows.agg(F.array(*[F.sum(F.col("d") * F.col(x)[k]) for k in range(dim)]).alias("g"), F.sum("l").alias("l"), F.count("*").alias("n")).first()
        if not s.n:
            break
        report.loss.append(s.l / s.n)
        w = [v - eta * g / s.n for v, g in zip(w, s.g)]
        models.append(w)
    return w, report, models


def bgd_feature_table(records: DataFrame, entries: DataFrame, loss: str = "logistic", eta: float = 0.5, iterations: int = 5, key: str = "id", layout: str | None = None, limit_bytes: float = 64e6) -> DataFrame:
    """(feature, weight) for models of many features: weights are a table.

    records: (id, y); entries: (id, feature, x). A copy of the entries stays partitioned by id, so slopes meet them without a shuffle and gradients are combined
    by feature before theirs. layout, chosen by the counted size of the model where not given: `broadcast_dense` brings the weights to the entries, so a round
    shuffles gradients only; `feature_table` joins them with a second copy of the entries, partitioned by feature, and shuffles the products by id."""
    parts = int(entries.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    by_id = entries.select(key, "feature", "x").repartition(parts, key).persist(StorageLevel.MEMORY_AND_DISK)
    y = records.select(key, F.col("y").cast("double").alias("y")).repartition(parts, key).persist(StorageLevel.MEMORY_AND_DISK)
    n = max(y.count(), 1)
    w = version(by_id.groupBy("feature").agg(F.lit(0.0).alias("weight")), "weights")
    size = w.agg(F.count("*").alias("dim"), F.max(F.octet_length(F.col("feature").cast("string"))).alias("longest")).first()
    layout = layout or choose_layout(size.dim, limit_bytes, 48 + (size.longest or 0))
    by_feature = by_id.repartition(parts, "feature").persist(StorageLevel.MEMORY_AND_DISK) if layout == "feature_table" else None
    for _ in range(iterations):
        met = by_id.join(F.broadcast(w), "feature") if by_feature is None else by_feature.join(w, "feature")
        p = met.groupBy(key).agg(F.sum(F.col("x") * F.col("weight")).alias("p"))
        slope = y.join(p, key, "left").select(key, value_and_slope(loss, F.coalesce("p", F.lit(0.0)), F.col("y"))[1].alias("d"))
        g = by_id.join(slope, key).groupBy("feature").agg(F.sum(F.col("x") * F.col("d")).alias("g"))
        w = version(w.join(g, "feature", "left").select("feature", (F.col("weight") - F.lit(eta) * F.coalesce("g", F.lit(0.0)) / n).alias("weight")), "weights")
    for df in (by_id, y, by_feature):
        if df is not None:
            df.unpersist()
    return w


def ols(train: DataFrame, features: list[str], label: str = "y") -> list[float]:
    """Least squares by the normal equations: one round, d^2 sums."""
    import numpy as np

    d = len(features)
    x = [F.col(f) for f in features]
    pairs = [(i, j) for i in range(d) for j in range(i, d)]
    s = train.agg(*[F.sum(x[i] * x[j]).alias(f"a{i}_{j}") for i, j in pairs], *[F.sum(x[i] * F.col(label)).alias(f"b{i}") for i in range(d)]).first()
    a = np.zeros((d, d))
    for i, j in pairs:
        a[i, j] = a[j, i] = s[f"a{i}_{j}"]
    return np.linalg.solve(a, np.array([s[f"b{i}"] for i in range(d)])).tolist()


def kmeans(points: DataFrame, centres: list[list[float]], iterations: int, x: str = "x") -> tuple[list[list[float]], list[int]]:
    """(centres, sizes): the nearest centre (ties: the first) in generated code, means as one sum a component."""
    dim, sizes = len(centres[0]), [0] * len(centres)
    for _ in range(iterations):
        dist = [F.aggregate(F.zip_with(F.col(x), F.array(*[F.lit(float(v)) for v in c]), lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v) for c in centres]
        near = F.array_position(F.array(*dist), F.array_min(F.array(*dist))) - 1
        s = points.select(near.alias("c"), x).groupBy("c").agg(F.array(*[F.avg(F.col(x)[k]) for k in range(dim)]).alias("m"), F.count("*").alias("n")).collect()
        got = {r.c: r for r in s}
        centres = [list(got[k].m) if k in got else c for k, c in enumerate(centres)]
        sizes = [int(got[k].n) if k in got else 0 for k in range(len(centres))]
    return centres, sizes


def gaussian_bayes(train: DataFrame, dim: int, x: str = "x", label: str = "y", floor: float = 1e-9) -> list[tuple]:
    """[(class, records, means, variances)] in one round: a map-reduce-update task without iteration. Classes, few as labels are, come to the driver; records don't.

    Variances are those of the population plus `floor`, so a constant component has a density. Records without a label or vector take no part."""
    v = [F.col(x)[k] for k in range(dim)]
    rows = train.where(F.col(label).isNotNull() & F.col(x).isNotNull()).groupBy(label)
    got = rows.agg(F.count("*").alias("n"), F.array(*[F.avg(c) for c in v]).alias("m"), F.array(*[F.var_pop(c) + floor for c in v]).alias("s")).collect()
    return sorted((r[label], r.n, list(r.m), list(r.s)) for r in got)


def gaussian_bayes_predict(df: DataFrame, model: list[tuple], x: str = "x") -> DataFrame:
    """df with `prediction`: the class of the largest log density and prior; ties to the smaller class."""

    def density(n, m, s):
        terms = F.zip_with(F.zip_with(F.col(x), F.array(*[F.lit(float(v)) for v in m]), lambda a, b: (a - b) * (a - b)), F.array(*[F.lit(float(v)) for v in s]), lambda q, b: q / b)
        return F.lit(math.log(n) - sum(math.log(v) for v in s) / 2) - F.aggregate(terms, F.lit(0.0), lambda a, b: a + b) / 2

    scores = F.array(*[density(*c[1:]) for c in model])
    return df.withColumn("prediction", F.element_at(F.array(*[F.lit(c[0]) for c in model]), F.array_position(scores, F.array_max(scores)).cast("int")))


def grid_search(train: DataFrame, grid: DataFrame, features: list[str], label: str = "y") -> DataFrame:
    """(candidate, loss) of every weight vector of a bounded grid, in one pass over the records. grid: (candidate, w array<double>)."""
    p = sum((F.col("w")[k] * F.col(f) for k, f in enumerate(features)), F.lit(0.0))
    rows = train.select(*features, label).crossJoin(F.broadcast(grid))
    return rows.groupBy("candidate").agg((F.sum(value_and_slope("squared", p, F.col(label))[0]) / F.count("*")).alias("loss"))


def predict(df: DataFrame, weights: list[float], features: list[str], loss: str = "squared") -> DataFrame:
    p = sum((F.lit(float(w)) * F.col(f) for w, f in zip(weights, features)), F.lit(0.0))
    return df.withColumn("prediction", F.lit(1.0) / (F.lit(1.0) + F.exp(-p)) if loss == "logistic" else p)


def evaluate(scored: DataFrame, label: str = "y", p: str = "prediction") -> DataFrame:
    """accuracy, log_loss, rmse and auc (ties count half) of 0/1 labels and probabilities.

    Scores are rounded to 9 decimals, so each of the 4096 stretches they are ranked in has less than 250,000 distinct ones, however many rows there are."""
    y, q = F.col(label), F.least(F.greatest(F.col(p), F.lit(1e-15)), F.lit(1 - 1e-15))
    simple = scored.agg(F.avg(F.when((F.col(p) >= 0.5) == (y > 0), 1.0).otherwise(0.0)).alias("accuracy"), F.avg(-F.when(y > 0, F.log(q)).otherwise(F.log(1 - q))).alias("log_loss"), F.sqrt(F.avg((F.col(p) - y) * (F.col(p) - y))).alias("rmse"))
    # distinct scores only; running sums within a stretch of scores, and over the at most 4097 totals of stretches
    by = scored.groupBy(F.round(p, 9).alias("s")).agg(F.sum(y.cast("long")).alias("pos"), F.count("*").alias("n")).withColumn("part", F.floor(F.col("s") * 4096))
    before = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    totals = by.groupBy("part").agg(F.sum(F.col("n") - F.col("pos")).alias("neg"))
    totals = totals.select(F.col("part").alias("stretch"), F.coalesce(F.sum("neg").over(before(Window.orderBy("part"))), F.lit(0)).alias("base"))
    run = by.withColumn("within", F.sum(F.col("n") - F.col("pos")).over(before(Window.partitionBy("part").orderBy("s"))))
    run = run.join(F.broadcast(totals), F.col("part").eqNullSafe(F.col("stretch"))).withColumn("below", F.col("base") + F.coalesce("within", F.lit(0)))
    auc = run.agg(F.try_divide(F.sum(F.col("pos") * (F.coalesce("below", F.lit(0)) + (F.col("n") - F.col("pos")) / 2)), F.sum("pos") * F.sum(F.col("n") - F.col("pos"))).alias("auc"))
    return simple.crossJoin(auc)
