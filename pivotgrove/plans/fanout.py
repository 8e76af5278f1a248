"""How many children a node gets: path-length objectives and their solvers, all on a few numbers."""

from __future__ import annotations

import math
import random
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

T_MIN, T_MAX = 2, 10


def levels(n: int, c: int, t: int) -> int:
    """Least number of levels that brings n points to c or fewer a leaf, by integer powers."""
    out, room = 0, c
    while room < n:
        room, out = room * t, out + 1
    return out


def leaf_fill(n: int, c: int, t: int) -> int:
    """Points in a typical leaf; halves go down."""
    whole, rest = divmod(n, t ** levels(n, c, t))
    return whole + (2 * rest > t ** levels(n, c, t))


def node_cost(t: int) -> float:
    """Comparisons to find each of t children by scanning t - 1 cuts, summed: 1, 2, ..., t - 1 and t - 1 again."""
    return t * t / 2 + t / 2 - 1


def aepl_printed(n: int, c: int, t: int) -> float:
    return (leaf_fill(n, c, t) * node_cost(t)) ** levels(n, c, t)


def aepl_printed_per_point(n: int, c: int, t: int) -> float:
    return aepl_printed(n, c, t) / n


def aepl_level_sum(n: int, c: int, t: int) -> float:
    """Levels times the mean comparisons in a node."""
    return levels(n, c, t) * node_cost(t) / t


def aepl_recursive(n: int, c: int, t: int) -> float:
    """Exact for equal-count cuts: children differ by one point at most and the first ones are smaller."""
    memo: dict[int, float] = {}

    def total(m: int) -> float:
        if m <= c:
            return 0.0
        if m not in memo:
            sizes = [(i + 1) * m // t - i * m // t for i in range(t)]
            memo[m] = sum(s * min(i + 1, t - 1) + total(s) for i, s in enumerate(sizes))
        return memo[m]

    return total(n) / n if n else 0.0


OBJECTIVES: dict[str, Callable[[int, int, int], float]] = {"printed": aepl_printed, "printed_per_point": aepl_printed_per_point, "level_sum": aepl_level_sum, "exact_recursive": aepl_recursive}


def allowed(n: int, c: int, t: int) -> bool:
    """A fan-out needs a point for each leaf, and no more children than leaves are wanted."""
    return t >= 2 and leaf_fill(n, c, t) >= 1 and t <= max(2, -(-n // c))


def optimal_fanout(n: int, c: int, t_min: int = T_MIN, t_max: int = T_MAX, objective: str = "printed", method: str = "scan", seed: int = 0, steps: int = 400, heat: float = 1.0, cooling: float = 0.98) -> int:
    """The fan-out of least objective in [t_min, t_max]; `anneal` walks to neighbours and takes worse ones by chance."""
    cost = OBJECTIVES[objective]
    options = [t for t in range(max(2, t_min), t_max + 1) if allowed(n, c, t)] or [2]
    if method == "scan":
        return min(options, key=lambda t: (cost(n, c, t), t))
    if method != "anneal":
        raise ValueError(f"unknown method {method}")
    draw = random.Random(seed)
    at = best = draw.randrange(len(options))
    score = [math.log(max(cost(n, c, t), 1e-300)) for t in options]
    span = max(score) - min(score) or 1.0
    for _ in range(steps):
        to = min(max(at + draw.choice((-2, -1, 1, 2)), 0), len(options) - 1)
        if score[to] <= score[at] or draw.random() < math.exp((score[at] - score[to]) / (heat * span)):
            at = to
        if (score[at], options[at]) < (score[best], options[best]):
            best = at
        heat = max(heat * cooling, 1e-3)
    return options[best]


def fanout_table(spark: SparkSession, n: int, c: int, t_min: int = T_MIN, t_max: int = T_MAX) -> DataFrame:
    """(t, levels, c0, printed, per_point, level_sum) over a range of fan-outs, as Column arithmetic."""
    out = spark.range(t_min, t_max + 1).select(F.col("id").cast("int").alias("t"))
    powers = F.sequence(F.lit(0), F.lit(64))
    height = F.aggregate(powers, F.lit(0), lambda s, i: F.when((F.lit(float(c)) * F.pow(F.col("t").cast("double"), i.cast("double")) < n) & (s == i), s + 1).otherwise(s))
    out = out.withColumn("levels", height)
    share = F.lit(float(n)) / F.pow(F.col("t").cast("double"), F.col("levels").cast("double"))
    out = out.withColumn("c0", F.when(share - F.floor(share) > 0.5, F.ceil(share)).otherwise(F.floor(share)).cast("long"))
    cost = F.col("t") * F.col("t") / 2.0 + F.col("t") / 2.0 - 1.0
    printed = F.pow(F.col("c0") * cost, F.col("levels").cast("double"))
    return out.select("t", "levels", "c0", printed.alias("printed"), (printed / n).alias("per_point"), (F.col("levels") * cost / F.col("t")).alias("level_sum"))
