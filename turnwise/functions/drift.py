"""Drift as set algebra over commitment arrays; every function is a plain column expression."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

NOT_DRIFT, VALUE, CONSTRAINT, PROJECTION, REJECT = "not_drift", "value", "constraint", "projection", "reject"


def item(kind: str, skeleton: str, *literals: Column, scope: str = "") -> Column:
    """A commitment struct, with its fields in the one order that set functions need."""
    held = F.array(*[l.cast("string") for l in literals]) if literals else F.array().cast("array<string>")
    return F.struct(F.lit(kind).alias("kind"), F.lit(scope).alias("scope"), F.lit(skeleton).alias("skeleton"), held.alias("literals"))


def _is_filter(x: Column, having_as_filter: bool) -> Column:
    return (x["kind"] == "FILTER") | (x["kind"] == "HAVING") if having_as_filter else x["kind"] == "FILTER"


def filters_of(s: Column, having_as_filter: bool = False) -> Column:
    return F.filter(s, lambda x: _is_filter(x, having_as_filter))


def outputs_of(s: Column, having_as_filter: bool = False) -> Column:
    return F.filter(s, lambda x: ~_is_filter(x, having_as_filter))


def split(s: Column, having_as_filter: bool = False) -> tuple[Column, Column]:
    """(filtering, output-side) parts of a commitment set."""
    return filters_of(s, having_as_filter), outputs_of(s, having_as_filter)


def is_drift(pre: Column, post: Column) -> Column:
    """Whether some earlier commitment is missing later; what was added does not matter."""
    return F.size(F.array_except(pre, post)) > 0


def delta(pre: Column, post: Column) -> Column:
    return F.struct(F.array_except(pre, post).alias("lost"), F.array_except(post, pre).alias("gained"), F.array_intersect(pre, post).alias("kept"))


def same_set(a: Column, b: Column) -> Column:
    return (F.size(F.array_except(a, b)) == 0) & (F.size(F.array_except(b, a)) == 0)


def single_literal_swap(w_pre: Column, w_post: Column) -> Column:
    """One filter lost, one gained, same structure, and one literal differs (for lists: one member out, one in)."""
    lost, gained = F.array_except(w_pre, w_post), F.array_except(w_post, w_pre)
    a, b = F.get(lost, F.lit(0)), F.get(gained, F.lit(0))
    same = (a["kind"] == b["kind"]) & (a["scope"] == b["scope"]) & (a["skeleton"] == b["skeleton"]) & (F.size(a["literals"]) == F.size(b["literals"]))
    is_list = F.contains(a["skeleton"], F.lit(" IN (?"))
    by_place = F.aggregate(F.zip_with(a["literals"], b["literals"], lambda x, y: F.when(x.eqNullSafe(y), 0).otherwise(1)), F.lit(0), lambda n, x: n + x)
    by_set = F.greatest(F.size(F.array_except(a["literals"], b["literals"])), F.size(F.array_except(b["literals"], a["literals"])))
    return (F.size(lost) == 1) & (F.size(gained) == 1) & F.coalesce(same & (F.when(is_list, by_set).otherwise(by_place) == 1), F.lit(False))


def classify(pre: Column, post: Column, having_as_filter: bool = False) -> Column:
    """Drift status and subtype; the first branch that holds decides. Null in, null out."""
    w1, o1 = split(pre, having_as_filter)
    w2, o2 = split(post, having_as_filter)
    label = (
        F.when(~is_drift(pre, post), NOT_DRIFT)
        .when(same_set(o1, o2) & single_literal_swap(w1, w2), VALUE)
        .when(same_set(o1, o2) & (F.size(F.array_except(w1, w2)) > 0) & (F.size(F.array_except(w2, w1)) == 0), CONSTRAINT)
        .when(same_set(w1, w2) & (F.size(F.array_except(o1, o2)) > 0), PROJECTION)
        .otherwise(REJECT)
    )
    return F.when(pre.isNotNull() & post.isNotNull(), label)


def admissible(s: Column, having_as_filter: bool = False) -> Column:
    """The subtypes that a query can support."""
    can_value = F.exists(s, lambda x: _is_filter(x, having_as_filter) & (F.size(x["literals"]) > 0))
    can_constraint = F.exists(s, lambda x: _is_filter(x, having_as_filter))
    can_projection = F.exists(s, lambda x: ~_is_filter(x, having_as_filter))
    return F.array_compact(F.array(F.when(can_value, VALUE), F.when(can_constraint, CONSTRAINT), F.when(can_projection, PROJECTION)))


def lost(long_pre: DataFrame, long_post: DataFrame, key: str | list[str]) -> DataFrame:
    """Relational form: rows of long_pre (key, kind, scope, skeleton, literals) without a partner in long_post."""
    keys = [key] if isinstance(key, str) else list(key)
    return long_pre.join(long_post, [*keys, "kind", "scope", "skeleton", "literals"], "left_anti")


def targeted_recognition(agent_pre: Column, agent_post: Column, gold_pre: Column, gold_post: Column) -> Column:
    """Beside the plain test: what the gold dropped is gone, and what the gold kept is still there."""
    gone = F.array_except(gold_pre, gold_post)
    stayed = F.array_intersect(gold_pre, gold_post)
    still = F.size(F.array_except(F.array_intersect(stayed, agent_pre), agent_post)) == 0
    return is_drift(agent_pre, agent_post) & (F.size(F.array_intersect(gone, agent_post)) == 0) & still
