"""The seven dialogue measures, and the baselines beside them, from one pass over trajectories.

Each measure is a numerator and a denominator, so that parts merge; an empty population gives a null value.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .trajectory import all_matched

DRIFT_TYPES, CHAIN_TYPES = ("D", "J"), ("C", "J")


def _of(types: tuple[str, ...] | None, protocol: str) -> Column:
    ok = F.col("protocol") == protocol
    return ok & F.col("sample_type").isin(*types) if types else ok


def _hit(layer: str) -> Column:
    return F.array_contains("rho", layer)


def definitions() -> dict[str, tuple[Column, Column]]:
    """measure -> (event, population) over columns protocol, sample_type, n_targets, asked, rho, ex, rec."""
    rec = F.coalesce(F.col("rec"), F.lit(False))
    post = F.coalesce(F.get("ex", F.lit(1)) == 1, F.lit(False))
    return {
        "dea": (all_matched(F.col("ex"), F.col("n_targets")), _of(None, "f")),
        "ar": (F.col("asked"), _of(None, "f")),
        "l1_ir": (_hit("L1"), _of(CHAIN_TYPES, "f")),
        "l2_ir_p": (_hit("L2"), _of(CHAIN_TYPES, "p")),
        "jir": (_hit("L1") & _hit("L2"), _of(CHAIN_TYPES, "f")),
        "drr": (rec, _of(DRIFT_TYPES, "f")),
        "dra": (rec & post, _of(DRIFT_TYPES, "f")),
        "pre_ex": (F.coalesce(F.get("ex", F.lit(0)) == 1, F.lit(False)), _of(None, "f")),
        "post_ex": (post, _of(DRIFT_TYPES, "f")),
        "plain_ex": (F.coalesce(F.element_at("ex", -1) == 1, F.lit(False)), _of(None, "f") & (F.size("ex") >= 0)),
        "per_turn_l1": (_hit("L1"), _of(CHAIN_TYPES, "f")),
        "per_turn_l2": (_hit("L2"), _of(CHAIN_TYPES, "f")),
    }


def wide(trajectories: DataFrame, by: list[str], names: list[str]) -> DataFrame:
    """by, then <measure>_num and <measure>_den for the measures named: one aggregate."""
    sums = []
    for name in names:
        event, population = definitions()[name]
        sums += [F.count_if(event & population).alias(f"{name}_num"), F.count_if(population).alias(f"{name}_den")]
    return trajectories.groupBy(*by).agg(*sums)


def measure(trajectories: DataFrame, name: str, by: list[str]) -> DataFrame:
    """by, num, den, value."""
    one = wide(trajectories, by, [name])
    return one.select(*by, F.col(f"{name}_num").alias("num"), F.col(f"{name}_den").alias("den"), F.try_divide(F.col(f"{name}_num").cast("double"), F.col(f"{name}_den")).alias("value"))


def all_metrics(trajectories: DataFrame, by: list[str]) -> DataFrame:
    """by, metric, num, den, value of every measure, from one aggregate."""
    names = list(definitions())
    rows = F.array(*[F.struct(F.lit(n).alias("metric"), F.col(f"{n}_num").alias("num"), F.col(f"{n}_den").alias("den")) for n in names])
    return wide(trajectories, by, names).select(*by, F.inline(rows)).withColumn("value", F.try_divide(F.col("num").cast("double"), F.col("den")))


def dea(t: DataFrame, by: list[str]) -> DataFrame:
    return measure(t, "dea", by)


def ar(t: DataFrame, by: list[str]) -> DataFrame:
    return measure(t, "ar", by)


def l1_ir(t: DataFrame, by: list[str]) -> DataFrame:
    return measure(t, "l1_ir", by)


def l2_ir_p(t: DataFrame, by: list[str]) -> DataFrame:
    return measure(t, "l2_ir_p", by)


def jir(t: DataFrame, by: list[str]) -> DataFrame:
    return measure(t, "jir", by)


def drr(t: DataFrame, by: list[str]) -> DataFrame:
    return measure(t, "drr", by)


def dra(t: DataFrame, by: list[str]) -> DataFrame:
    return measure(t, "dra", by)


def plain_ex(t: DataFrame, by: list[str]) -> DataFrame:
    """Baseline: execution match of the final query alone."""
    return measure(t, "plain_ex", by)


def per_turn_ambiguity(t: DataFrame, by: list[str]) -> DataFrame:
    """Baseline: each layer scored alone, without the dependency."""
    return wide(t, by, ["per_turn_l1", "per_turn_l2"])
