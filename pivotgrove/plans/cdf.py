"""Learned distribution functions: a root line that deals values to sub-models, each a line of its own.

Two forms of the same model: numpy for a node inside a kernel, DataFrame aggregates for all nodes of a level.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


@dataclass
class Cdf:
    alpha: float
    beta: float
    xlo: np.ndarray  # by sub-model: line from (xlo, flo) to (xhi, fhi)
    xhi: np.ndarray
    flo: np.ndarray
    fhi: np.ndarray

    def route(self, x: np.ndarray) -> np.ndarray:
        return np.clip(np.floor(self.alpha * x + self.beta), 0, len(self.xlo) - 1).astype(np.int64)

    def predict(self, x: np.ndarray) -> np.ndarray:
        u = self.route(x)
        width = self.xhi[u] - self.xlo[u]
        share = np.clip(np.where(width > 0, (x - self.xlo[u]) / np.where(width > 0, width, 1), 0.5), 0, 1)
        return self.flo[u] + share * (self.fhi[u] - self.flo[u])

    def inverse(self, q: float) -> float:
        """The value at which the prediction reaches q."""
        u = min(int(np.searchsorted(self.fhi, q)), len(self.xlo) - 1)
        rise = self.fhi[u] - self.flo[u]
        share = min(max((q - self.flo[u]) / rise, 0.0), 1.0) if rise > 0 else 1.0
        return float(self.xlo[u] + share * (self.xhi[u] - self.xlo[u]))


def fit(sample: np.ndarray, l: int, sub: str = "extremes") -> Cdf:  # noqa: E741
    """Fit on a sample. sub: "extremes" (lines through each part's ends) or "squares" (least squares)."""
    x = np.sort(np.asarray(sample, dtype=float))
    n = len(x)
    f = np.arange(n) / n
    mx, mu = x.mean(), (l * f).mean()
    spread = ((x - mx) ** 2).sum()
    alpha = float(((x - mx) * (l * f - mu)).sum() / spread) if spread > 0 else 0.0
    beta = float(mu - alpha * mx)
    u = np.clip(np.floor(alpha * x + beta), 0, l - 1).astype(np.int64)
    used, first = np.unique(u, return_index=True)
    last = np.append(first[1:], n) - 1
    xlo, xhi, flo, fhi = x[first], x[last], f[first], f[last]
    if sub == "squares":
        for i, (a, b) in enumerate(zip(first, last + 1, strict=True)):
            px, pf = x[a:b], f[a:b]
            s = ((px - px.mean()) ** 2).sum()
            k = ((px - px.mean()) * (pf - pf.mean())).sum() / s if s > 0 else 0.0
            flo[i], fhi[i] = (pf.mean() + k * (e - px.mean()) for e in (px[0], px[-1]))
    # A part that got no value spans from its left neighbour's end to its right neighbour's beginning.
    full = [np.empty(l) for _ in range(4)]
    left = np.searchsorted(used, np.arange(l), side="right") - 1
    right = np.minimum(np.searchsorted(used, np.arange(l)), len(used) - 1)
    held = np.isin(np.arange(l), used)
    left0 = np.maximum(left, 0)
    full[0] = np.where(held, xlo[left0], np.where(left >= 0, xhi[left0], xlo[0]))
    full[1] = np.where(held, xhi[left0], xlo[right])
    full[2] = np.where(held, flo[left0], np.where(left >= 0, fhi[left0], flo[0]))
    full[3] = np.where(held, fhi[left0], flo[right])
    full[1], full[3] = np.maximum(full[0], full[1]), np.maximum(full[2], full[3])
    return Cdf(alpha, beta, *full)


# --- all nodes at once -------------------------------------------------------------------------------------


def cdf_sample(df: DataFrame, delta: float, seed: int = 0, pid: str = "pid", keys: list[str] | None = None, least: int = 0) -> DataFrame:
    """A share delta of the rows by hash of the id, the same whatever the partitioning; with keys, `least` rows each at least."""
    draw = F.pmod(F.xxhash64(F.col(pid), F.lit(seed)), F.lit(1_000_000))
    if not (keys and least):
        return df.where(draw < int(delta * 1_000_000))
    order = Window.partitionBy(*keys).orderBy(draw, pid)
    return df.withColumn("_draw", draw).withColumn("_at", F.row_number().over(order)).where(f"_draw < {int(delta * 1_000_000)} or _at <= {least}").drop("_draw", "_at")


def empirical_cdf(sample: DataFrame, keys: list[str], x: str, pid: str = "pid", kind: str = "rank") -> DataFrame:
    """Adds f: zero-based rank over size by (x, pid); or Spark's percent_rank, cume_dist."""
    by = Window.partitionBy(*keys)
    if kind == "rank":
        f = (F.row_number().over(by.orderBy(x, pid)) - 1) / F.count("*").over(by)
    else:
        f = {"percent_rank": F.percent_rank, "cume_dist": F.cume_dist}[kind]().over(by.orderBy(x))
    return sample.withColumn("f", f)


def root_sums(ecdf: DataFrame, keys: list[str], x: str, l: int) -> DataFrame:  # noqa: E741
    u = F.col("f") * l
    return ecdf.groupBy(*keys).agg(F.count("*").alias("n"), F.sum(x).alias("sx"), F.sum(F.col(x) * F.col(x)).alias("sxx"), F.sum(u).alias("su"), F.sum(F.col(x) * u).alias("sxu"))


def root_line(sums: DataFrame) -> DataFrame:
    """Adds alpha and beta from the sums; with no spread in x the line is level."""
    det = F.col("n") * F.col("sxx") - F.col("sx") * F.col("sx")
    out = sums.withColumn("alpha", F.when(F.abs(det) <= F.lit(1e-12) * F.greatest(F.abs(F.col("n") * F.col("sxx")), F.lit(1e-300)), 0.0).otherwise((F.col("n") * F.col("sxu") - F.col("sx") * F.col("su")) / det))
    return out.withColumn("beta", (F.col("su") - F.col("alpha") * F.col("sx")) / F.col("n"))


def fit_root(ecdf: DataFrame, keys: list[str], x: str, l: int) -> DataFrame:  # noqa: E741
    return root_line(root_sums(ecdf, keys, x, l))


def refit_root(model: DataFrame, inserted: DataFrame, departed: DataFrame, keys: list[str]) -> DataFrame:
    """The line after rows came and went: each frame holds sums (n, sx, sxx, su, sxu); departed ones count negative."""
    names = ["n", "sx", "sxx", "su", "sxu"]
    gone = departed.select(*keys, *[(-F.col(c)).alias(c) for c in names])
    total = model.select(*keys, *names).unionByName(inserted.select(*keys, *names)).unionByName(gone)
    return root_line(total.groupBy(*keys).agg(*[F.sum(c).alias(c) for c in names]))


def submodel_of(x: Column, l: int) -> Column:  # noqa: E741
    return F.greatest(F.lit(0), F.least(F.lit(l - 1), F.floor(F.col("alpha") * x + F.col("beta")))).cast("int")


def fit_sub_plf(ecdf: DataFrame, roots: DataFrame, keys: list[str], x: str, l: int) -> DataFrame:  # noqa: E741
    """(keys, u, xlo, xhi, flo, fhi): each part's line through its ends, in one hash aggregation."""
    dealt = ecdf.join(F.broadcast(roots.select(*keys, "alpha", "beta")), keys) if keys else ecdf.crossJoin(F.broadcast(roots.select("alpha", "beta")))
    dealt = dealt.withColumn("u", submodel_of(F.col(x), l))
    return dealt.groupBy(*keys, "u").agg(F.min(x).alias("xlo"), F.max(x).alias("xhi"), F.min("f").alias("flo"), F.max("f").alias("fhi"), F.count("*").alias("n"))


def fit_sub_lsq(ecdf: DataFrame, roots: DataFrame, keys: list[str], x: str, l: int) -> DataFrame:  # noqa: E741
    dealt = ecdf.join(F.broadcast(roots.select(*keys, "alpha", "beta")), keys) if keys else ecdf.crossJoin(F.broadcast(roots.select("alpha", "beta")))
    dealt = dealt.withColumn("u", submodel_of(F.col(x), l))
    return dealt.groupBy(*keys, "u").agg(F.regr_slope(F.col("f"), F.col(x)).alias("slope"), F.regr_intercept(F.col("f"), F.col(x)).alias("intercept"), F.count("*").alias("n"))


def fill_subs(subs: DataFrame, keys: list[str], l: int) -> DataFrame:  # noqa: E741
    """subs with a row for every part: one without values spans from its left neighbour's end to its right one's begin."""
    every = subs.select(*keys).distinct().withColumn("u", F.explode(F.sequence(F.lit(0), F.lit(l - 1))))
    by = Window.partitionBy(*keys).orderBy("u")
    left, right = by.rowsBetween(Window.unboundedPreceding, 0), by.rowsBetween(0, Window.unboundedFollowing)
    out = every.join(subs, [*keys, "u"], "left")
    seen = {c: (F.last(c, ignorenulls=True).over(left), F.first(c, ignorenulls=True).over(right)) for c in ("xlo", "xhi", "flo", "fhi")}
    ends = {
        "xlo": F.coalesce("xlo", seen["xhi"][0], seen["xlo"][1]),
        "xhi": F.coalesce("xhi", seen["xlo"][1], seen["xhi"][0]),
        "flo": F.coalesce("flo", seen["fhi"][0], seen["flo"][1]),
        "fhi": F.coalesce("fhi", seen["flo"][1], seen["fhi"][0]),
    }
    return out.select(*keys, "u", *[e.alias(c) for c, e in ends.items()])


def predict_cdf(df: DataFrame, roots: DataFrame, subs: DataFrame, keys: list[str], x: str, l: int) -> DataFrame:  # noqa: E741
    """Adds predicted: models are joined by node and part (a few hundred rows a node), parts without values give null."""
    base = df.join(F.broadcast(roots.select(*keys, "alpha", "beta")), keys) if keys else df.crossJoin(F.broadcast(roots.select("alpha", "beta")))
    base = base.withColumn("u", submodel_of(F.col(x), l)).join(F.broadcast(subs.select(*keys, "u", "xlo", "xhi", "flo", "fhi")), [*keys, "u"], "left")
    width = F.col("xhi") - F.col("xlo")
    share = F.when(width > 0, F.greatest(F.lit(0.0), F.least(F.lit(1.0), (F.col(x) - F.col("xlo")) / width))).otherwise(0.5)
    return base.withColumn("predicted", F.col("flo") + share * (F.col("fhi") - F.col("flo"))).drop("alpha", "beta", "u", "xlo", "xhi", "flo", "fhi")


def cdf_error(predicted: DataFrame, x: str, pid: str = "pid") -> DataFrame:
    """Greatest and mean absolute error against the zero-based rank over size."""
    by = Window.partitionBy()
    rows = predicted.where("predicted is not null").withColumn("true_f", (F.row_number().over(by.orderBy(x, pid)) - 1) / F.count("*").over(by))
    gap = F.abs(F.col("predicted") - F.col("true_f"))
    return rows.agg(F.max(gap).alias("max_error"), F.avg(gap).alias("mean_error"), F.count("*").alias("n"))


def tune_submodels(values: np.ndarray, grid: tuple[int, ...] = (10, 50, 100, 500, 1000)) -> dict[int, float]:
    """Mean error of each number of sub-models on a driver-held sample."""
    x = np.sort(np.asarray(values, dtype=float))
    f = np.arange(len(x)) / max(1, len(x))
    return {l: float(np.abs(fit(x, l).predict(x) - f).mean()) for l in grid}
