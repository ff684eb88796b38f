"""Contrasts of the measures. Inputs are trajectories or small metric tables; results are small."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import metrics
from .trajectory import all_matched

def _ok() -> Column:
    return all_matched(F.col("ex"), F.col("n_targets"))


def rate(num: str, den: str) -> Column:
    return F.try_divide(F.col(num).cast("double"), F.col(den))


def accuracy_table(t: DataFrame) -> DataFrame:
    """agent, sample_type, subtype (null: all), num, den, dea."""
    f = t.filter("protocol = 'f'").withColumn("subtype", F.coalesce("subtype", F.lit("-")))
    sets = f.groupingSets([["agent", "sample_type", "subtype"], ["agent", "sample_type"]], "agent", "sample_type", "subtype")
    return sets.agg(F.count_if(_ok()).alias("num"), F.count("*").alias("den")).withColumn("dea", rate("num", "den"))


def rank_marks(table: DataFrame, by: str = "sample_type", value: str = "dea") -> DataFrame:
    r = F.dense_rank().over(Window.partitionBy(by).orderBy(F.desc(value)))
    return table.withColumn("rank_dense", r).withColumn("mark", F.when(r == 1, "best").when(r == 2, "second").otherwise(""))


def spread(table: DataFrame, by: str = "sample_type", value: str = "dea") -> DataFrame:
    return table.groupBy(by).agg(F.max(value).alias("best"), F.min(value).alias("worst"), (F.max(value) - F.min(value)).alias("spread"))


def by_type(t: DataFrame, name: str) -> DataFrame:
    """agent with one column C, D, J of a measure."""
    m = metrics.measure(t, name, ["agent", "sample_type"])
    return m.groupBy("agent").pivot("sample_type", ["C", "D", "J"]).agg(F.first("value"))


def ordering(t: DataFrame) -> DataFrame:
    return by_type(t, "dea").withColumn("ordered", (F.col("D") > F.col("C")) & (F.col("C") > F.col("J")))


def layer_contrast(t: DataFrame, types: tuple[str, ...] = ("C",)) -> DataFrame:
    """agent, l1_ir, l2_ir_p, jir: first-layer and joint rates of the full protocol, second-layer rate of the primed one."""
    w = metrics.wide(t.filter(F.col("sample_type").isin(*types)), ["agent"], ["l1_ir", "l2_ir_p", "jir"])
    return w.select("agent", *[rate(f"{n}_num", f"{n}_den").alias(n) for n in ("l1_ir", "l2_ir_p", "jir")])


def ask_vs_identify(t: DataFrame) -> DataFrame:
    w = metrics.wide(t.filter("sample_type = 'C'"), ["agent"], ["ar", "jir"])
    return w.select("agent", rate("ar_num", "ar_den").alias("ar"), rate("jir_num", "jir_den").alias("jir"))


def ask_correlation(t: DataFrame) -> DataFrame:
    return ask_vs_identify(t).agg(F.corr("ar", "jir").alias("correlation"))


def ask_selectivity(t: DataFrame) -> DataFrame:
    p = by_type(t, "ar")
    return p.select("agent", F.col("C").alias("ar_chain"), F.col("D").alias("ar_drift"), (F.col("C") - F.col("D")).alias("difference"))


def recognition(t: DataFrame, by: list[str] = ("agent", "sample_type")) -> DataFrame:
    """by, drr, dra, gap."""
    w = metrics.wide(t.filter(F.col("sample_type").isin("D", "J")), list(by), ["drr", "dra"])
    return w.select(*by, rate("drr_num", "drr_den").alias("drr"), rate("dra_num", "dra_den").alias("dra"), (rate("drr_num", "drr_den") - rate("dra_num", "dra_den")).alias("gap"))


def gap(t: DataFrame) -> DataFrame:
    return recognition(t).select("agent", "sample_type", "gap")


def subtype_profile(t: DataFrame) -> DataFrame:
    """Drift-only resolution by subtype and agent, with the subtype's mean and whether it is the subtype's best."""
    m = metrics.measure(t.filter("sample_type = 'D'"), "dra", ["subtype", "agent"]).filter("den > 0")
    w = Window.partitionBy("subtype")
    return m.select("subtype", "agent", F.col("value").alias("dra"), F.avg("value").over(w).alias("subtype_mean"), (F.col("value") == F.max("value").over(w)).alias("is_max"))


def extremes(profile: DataFrame) -> DataFrame:
    """How many agents find each subtype easiest and hardest."""
    per = profile.groupBy("agent").agg(F.max_by("subtype", F.struct("dra", "subtype")).alias("easiest"), F.min_by("subtype", F.struct("dra", "subtype")).alias("hardest"), (F.max("dra") - F.min("dra")).alias("difference"))
    rows = per.select(F.explode(F.array(F.struct(F.col("easiest").alias("subtype"), F.lit(1).alias("e"), F.lit(0).alias("h")), F.struct(F.col("hardest").alias("subtype"), F.lit(0).alias("e"), F.lit(1).alias("h")))).alias("x"))
    return rows.groupBy("x.subtype").agg(F.sum("x.e").alias("easiest_for"), F.sum("x.h").alias("hardest_for"))


def transition(t: DataFrame) -> DataFrame:
    """agent, change of drr, dra and dea from Drift-only to Joint, over anchors that have both."""
    both = t.filter("protocol = 'f' AND sample_type IN ('D', 'J')")
    flag = lambda c, k: F.max(F.when(F.col("sample_type") == k, c.cast("int")))
    events = {n: metrics.definitions()[n][0] for n in ("drr", "dra", "dea")}
    per = both.groupBy("agent", "anchor_id").agg(*[flag(e, k).alias(f"{n}_{k}") for n, e in events.items() for k in ("D", "J")])
    paired = per.filter(F.col("dea_D").isNotNull() & F.col("dea_J").isNotNull())
    return paired.groupBy("agent").agg(*[(F.avg(f"{n}_J") - F.avg(f"{n}_D")).alias(f"d_{n}") for n in events])


def joint_excess(t: DataFrame) -> DataFrame:
    p = by_type(t, "dea")
    return p.select("agent", (F.col("C") * F.col("D")).alias("product"), F.col("J").alias("joint"), (F.col("J") - F.col("C") * F.col("D")).alias("excess"))


def failure_overlap(t: DataFrame) -> DataFrame:
    """Per agent the contingency of Chain-only and Drift-only failures over anchors, with its lift, Jaccard index and phi."""
    f = t.filter("protocol = 'f'")
    fail = lambda k: F.max(F.when(F.col("sample_type") == k, (~_ok()).cast("int")))
    per = f.groupBy("agent", "anchor_id").agg(fail("C").alias("c"), fail("D").alias("d")).dropna(subset=["c", "d"])
    n = per.groupBy("agent").agg(
        F.sum(F.col("c") * F.col("d")).alias("both_fail"), F.sum(F.col("c") * (1 - F.col("d"))).alias("only_chain"), F.sum((1 - F.col("c")) * F.col("d")).alias("only_drift"),
        F.sum((1 - F.col("c")) * (1 - F.col("d"))).alias("neither"), F.try_divide(F.covar_pop("c", "d"), F.stddev_pop("c") * F.stddev_pop("d")).alias("phi"), F.count("*").alias("n"),
    )
    lift = F.try_divide(F.col("both_fail").cast("double") * F.col("n"), (F.col("both_fail") + F.col("only_chain")) * (F.col("both_fail") + F.col("only_drift")))
    return n.withColumn("lift", lift).withColumn("jaccard", F.try_divide(F.col("both_fail").cast("double"), F.col("both_fail") + F.col("only_chain") + F.col("only_drift")))


def trace(turns: DataFrame, run_id: str) -> DataFrame:
    return turns.filter(F.col("run_id") == run_id).orderBy("turn_no")


def inherited_error(rec: Column, ex: Column) -> Column:
    """Wrong before the drift, drift noticed, wrong after."""
    return (F.get(ex, F.lit(0)) == 0) & rec & (F.get(ex, F.lit(1)) == 0)


def class_contrast(table: DataFrame, classes: DataFrame, value: str = "dea") -> DataFrame:
    """Mean of large minus mean of small agents; classes: agent, size_class."""
    m = table.join(F.broadcast(classes), "agent")
    large, small = F.avg(F.when(F.col("size_class") == "large", F.col(value))), F.avg(F.when(F.col("size_class") == "small", F.col(value)))
    return m.groupBy("sample_type").agg(large.alias("large"), small.alias("small"), (large - small).alias("difference"))


def wilson(num: Column, den: Column, z: float = 1.96) -> Column:
    """struct<low, high> of a proportion."""
    p = num.cast("double") / den
    mid, half, scale = p + z * z / (2 * den), z * F.sqrt(p * (1 - p) / den + z * z / (4 * den * den)), 1 + z * z / den
    return F.when(den > 0, F.struct(((mid - half) / scale).alias("low"), ((mid + half) / scale).alias("high")))


def bootstrap_difference(t: DataFrame, name: str, a: str = "D", b: str = "J", replicates: int = 200, seed: int = 42) -> DataFrame:
    """agent, low, high of the paired difference b - a: Poisson(1) weights of anchors by hash, 95 % of the replicates."""
    event = metrics.definitions()[name][0]
    flag = lambda k: F.max(F.when(F.col("sample_type") == k, event.cast("int")))
    per = t.filter("protocol = 'f'").groupBy("agent", "anchor_id").agg(flag(a).alias("a"), flag(b).alias("b")).dropna()
    u = F.pmod(F.xxhash64(F.lit(seed), "anchor_id", "r"), F.lit(1_000_000)) / 1_000_000.0
    weight = F.lit(0)
    for k, upper in enumerate((0.367879, 0.735759, 0.919699, 0.981012, 0.996340)):  # cumulative Poisson(1)
        weight = F.when(u >= upper, k + 1).otherwise(weight)
    rows = per.withColumn("r", F.explode(F.sequence(F.lit(1), F.lit(replicates)))).withColumn("w", weight)
    each = rows.groupBy("agent", "r").agg(F.try_divide(F.sum(F.col("w") * (F.col("b") - F.col("a"))).cast("double"), F.sum("w")).alias("x"))
    return each.groupBy("agent").agg(F.percentile("x", 0.025).alias("low"), F.percentile("x", 0.975).alias("high"))


def post_complexity(samples: DataFrame, by: str = "subtype", score: str = "score") -> DataFrame:
    return samples.groupBy(by).agg(F.count("*").alias("n"), F.avg(score).alias("mean_score"))


def threshold_counts(table: DataFrame, levels: DataFrame) -> DataFrame:
    """metric, level, n_below, n_above, argmin, argmax over agents; table: agent, metric, value; levels: metric, level."""
    return table.join(F.broadcast(levels), "metric").groupBy("metric", "level").agg(
        F.count_if(F.col("value") < F.col("level")).alias("n_below"), F.count_if(F.col("value") > F.col("level")).alias("n_above"),
        F.min_by("agent", F.struct("value", "agent")).alias("argmin"), F.max_by("agent", F.struct("value", "agent")).alias("argmax"),
    )
