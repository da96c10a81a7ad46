"""Verification of pairs by the values behind the names, and by people's votes.

A pair that violates a rule is a false positive. Where an attribute has no values the rules say
``unknown``, and only votes can decide.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

AFFIX = 3


def family(kind: T.DataType) -> str:
    """The family of a type, for the comparison of pairs."""
    groups = [
        ((T.ByteType, T.ShortType, T.IntegerType, T.LongType), "integer"),
        ((T.FloatType, T.DoubleType, T.DecimalType), "fractional"),
        ((T.StringType, T.CharType, T.VarcharType), "text"),
        ((T.DateType, T.TimestampType, T.TimestampNTZType, T.DayTimeIntervalType, T.YearMonthIntervalType), "temporal"),
        ((T.BooleanType,), "boolean"),
        ((T.ArrayType,), "list"),
        ((T.MapType,), "map"),
        ((T.StructType,), "record"),
        ((T.BinaryType,), "binary"),
    ]
    return next((name for kinds, name in groups if isinstance(kind, kinds)), "other")


PROFILE = "schema_id string, attr string, family string, element_family string, prefix string, suffix string, n_values long"


def profile_table(schema_id: str, df: DataFrame, distinct: bool = False) -> DataFrame:
    """``schema_id, attr, family, element_family, prefix, suffix, n_values``: one pass, no shuffle of values.

    ``prefix`` and ``suffix`` are the first and last ``AFFIX`` characters if all values share them.
    ``distinct`` adds ``n_distinct``, which costs a row for each value and column; no rule needs it.
    """
    aggs, cells = [], []
    for i, field in enumerate(df.schema.fields):
        own = F.col(f"`{field.name}`")
        kind = family(field.dataType)
        aggs.append(F.count(own).alias(f"n{i}"))
        affixes = {"p": F.left(own, F.lit(AFFIX)), "s": F.right(own, F.lit(AFFIX))} if kind == "text" else {}
        for part, value in affixes.items():
            aggs.append(F.when(F.min(value) == F.max(value), F.min(value)).alias(f"{part}{i}"))
        affix = lambda part: F.col(f"{part}{i}") if part in affixes else F.lit(None).cast("string")  # noqa: B023, E731
        if distinct:
            flat = own.cast("string") if kind in ("integer", "fractional", "text", "temporal", "boolean") else F.to_json(own) if kind in ("list", "map", "record") else F.hex(own)
            aggs.append(F.count_distinct(flat).alias(f"d{i}"))
        element = family(field.dataType.elementType) if isinstance(field.dataType, T.ArrayType) else None
        cell = [F.lit(schema_id).alias("schema_id"), F.lit(field.name).alias("attr"), F.lit(kind).alias("family"), F.lit(element).cast("string").alias("element_family"), affix("p").alias("prefix"), affix("s").alias("suffix"), F.col(f"n{i}").alias("n_values")]
        cells.append(F.struct(*cell, *([F.col(f"d{i}").alias("n_distinct")] if distinct else [])))
    return df.agg(*aggs).select(F.inline(F.array(*cells)))


def profile_values(tables: dict[str, DataFrame], distinct: bool = False) -> DataFrame:
    return reduce(DataFrame.unionByName, [profile_table(name, df, distinct) for name, df in tables.items()])


def unpivot_values(tables: dict[str, DataFrame], columns: dict[str, list[str]] | None = None) -> DataFrame:
    """``schema_id, attr, value``: the distinct non-null values of each column, as text; one pass a table.

    ``columns`` names the columns of each table that are wanted; all by default.
    """
    parts = []
    for name, df in tables.items():
        kept = [c for c in df.columns if columns is None or c in columns.get(name, [])]
        if kept:
            cells = [F.struct(F.lit(c).alias("attr"), (F.to_json(F.col(f"`{c}`")) if family(df.schema[c].dataType) in ("list", "map", "record") else F.col(f"`{c}`").cast("string")).alias("value")) for c in kept]
            parts.append(df.select(F.lit(name).alias("schema_id"), F.inline(F.array(*cells))).where("value IS NOT NULL").distinct())
    return reduce(DataFrame.unionByName, parts)


def affix_support(tables: dict[str, DataFrame], min_support: float = 1.0) -> DataFrame:
    """``schema_id, attr, side, affix, support``: the commonest prefix and suffix of each text column, if
    at least ``min_support`` of its values share it; ties go to the least affix. A few odd values do
    not hide an affix here, as they do in ``profile_table``."""
    parts = []
    for name, df in tables.items():
        texts = [f.name for f in df.schema.fields if family(f.dataType) == "text"]
        if texts:
            cells = [F.struct(F.lit(c).alias("attr"), F.lit(side).alias("side"), cut_(F.col(f"`{c}`"), F.lit(AFFIX)).alias("affix")) for c in texts for side, cut_ in (("prefix", F.left), ("suffix", F.right))]
            parts.append(df.select(F.lit(name).alias("schema_id"), F.inline(F.array(*cells))).where("affix IS NOT NULL"))
    counted = reduce(DataFrame.unionByName, parts).groupBy("schema_id", "attr", "side", "affix").agg(F.count(F.lit(1)).alias("n"))
    best = counted.groupBy("schema_id", "attr", "side").agg(F.min(F.struct((-F.col("n")).alias("m"), "affix")).alias("b"), F.sum("n").alias("total"))
    return best.select("schema_id", "attr", "side", F.col("b.affix").alias("affix"), F.round(-F.col("b.m") / F.col("total"), 6).alias("support")).where(F.col("support") >= min_support)


def with_affixes(profile: DataFrame, support: DataFrame) -> DataFrame:
    """The profile with its affixes replaced by those of ``affix_support``."""
    side = lambda s: support.where(F.col("side") == s).select("schema_id", "attr", F.col("affix").alias(s))
    key = ["schema_id", "attr"]
    return profile.drop("prefix", "suffix").join(side("prefix"), key, "left").join(side("suffix"), key, "left")


def _sides(pairs: DataFrame, profile: DataFrame) -> DataFrame:
    """``pairs(schema_a, a, schema_b, b)`` with the profiles of both, as structs ``x`` and ``y``."""
    cols = ["family", "element_family", "prefix", "suffix", "n_values"]
    side = lambda s, a, name: profile.select(F.col("schema_id").alias(s), F.col("attr").alias(a), F.struct(*cols).alias(name))
    return pairs.join(side("schema_a", "a", "x"), ["schema_a", "a"], "left").join(side("schema_b", "b", "y"), ["schema_b", "b"], "left")


def _verdict(rows: DataFrame, rule: str, known: Column, holds: Column) -> DataFrame:
    verdict = F.when(~known | known.isNull(), "unknown").when(holds, "keep").otherwise("deny")
    return rows.select("schema_a", "a", "schema_b", "b", F.lit(rule).alias("rule"), verdict.alias("verdict"))


def rule_type(pairs: DataFrame, profile: DataFrame) -> DataFrame:
    """Values of a matching pair are of one type family; unknown where a side has no values."""
    known = (F.col("x.n_values") > 0) & (F.col("y.n_values") > 0)
    return _verdict(_sides(pairs, profile), "type", known, F.col("x.family") == F.col("y.family"))


def rule_structure(pairs: DataFrame, profile: DataFrame) -> DataFrame:
    """Lists match lists with elements of one family; unknown for pairs without lists."""
    known = (F.col("x.family") == "list") | (F.col("y.family") == "list")
    return _verdict(_sides(pairs, profile), "structure", known, F.col("x.family").eqNullSafe(F.col("y.family")) & F.col("x.element_family").eqNullSafe(F.col("y.element_family")))


def rule_affix(pairs: DataFrame, profile: DataFrame) -> DataFrame:
    """If all values of both sides share an affix each, one of them is common to both sides."""
    prefixes = F.col("x.prefix").isNotNull() & F.col("y.prefix").isNotNull()
    suffixes = F.col("x.suffix").isNotNull() & F.col("y.suffix").isNotNull()
    holds = F.coalesce(F.col("x.prefix") == F.col("y.prefix"), F.lit(False)) | F.coalesce(F.col("x.suffix") == F.col("y.suffix"), F.lit(False))
    return _verdict(_sides(pairs, profile), "affix", prefixes | suffixes, holds)


def rule_containment(pairs: DataFrame, values: DataFrame) -> DataFrame:
    """Values of one side all occur on the other: evidence for keys.

    ``values`` are those of ``unpivot_values``; all pairs are judged by one join on the values. Unknown
    where some value of each side is missing from the other, or a side has no values.
    """
    sizes = values.groupBy("schema_id", "attr").agg(F.count(F.lit(1)).alias("n"))
    key = ["schema_a", "a", "schema_b", "b"]
    own = pairs.select(*key).distinct()
    x = own.join(values.select(F.col("schema_id").alias("schema_a"), F.col("attr").alias("a"), "value"), ["schema_a", "a"])
    shared = x.join(values.select(F.col("schema_id").alias("schema_b"), F.col("attr").alias("b"), "value"), ["schema_b", "b", "value"]).groupBy(*key).agg(F.count(F.lit(1)).alias("shared"))
    size = lambda s, a, n: sizes.select(F.col("schema_id").alias(s), F.col("attr").alias(a), F.col("n").alias(n))
    met = own.join(shared, key, "left").join(size("schema_a", "a", "na"), ["schema_a", "a"], "left").join(size("schema_b", "b", "nb"), ["schema_b", "b"], "left")
    return met.select(*key, F.lit("containment").alias("rule"), F.when(F.col("shared") == F.least("na", "nb"), "keep").otherwise("unknown").alias("verdict"))


def verify_values(pairs: DataFrame, profile: DataFrame, rules=(rule_type, rule_structure)) -> tuple[DataFrame, DataFrame]:
    """``(kept, denied)``: pairs that no rule denies, and the denying verdicts. Any function of pairs and
    profile that gives ``schema_a, a, schema_b, b, rule, verdict`` may be among the rules."""
    verdicts = reduce(DataFrame.unionByName, [rule(pairs, profile) for rule in rules])
    denied = verdicts.where("verdict = 'deny'")
    key = ["schema_a", "a", "schema_b", "b"]
    return pairs.join(denied.select(*key).distinct(), key, "left_anti"), denied


def verify_names(pairs: DataFrame, schemas: DataFrame, profile: DataFrame, rules=(rule_type, rule_structure), by: tuple[str, ...] = ("family", "element_family")) -> DataFrame:
    """The name pairs ``(a, b)`` of which some pair of occurrences is denied by no rule.

    Occurrences of a name with equal profiles (in ``by``, and whether there are values) stand or fall
    together, so one schema for each kind is compared: a name in a million schemas has a handful of
    kinds. An occurrence without a profile is of a kind of its own, which nothing denies.
    """
    key = ["schema_id", "attr"]
    seen = schemas.select(*key).distinct().join(profile, key, "left")
    valued = (F.coalesce("n_values", F.lit(0)) > 0).alias("valued")
    kinds = seen.groupBy("attr", *by, valued, F.col("family").isNull().alias("unseen")).agg(F.min("schema_id").alias("schema_id"))
    side = lambda s, a: kinds.select(F.col("schema_id").alias(s), F.col("attr").alias(a))
    wide = pairs.select("a", "b").distinct().join(side("schema_a", "a"), "a").join(side("schema_b", "b"), "b").select("schema_a", "a", "schema_b", "b")
    kept, _ = verify_values(wide, profile, rules)
    return pairs.join(kept.select("a", "b").distinct(), ["a", "b"], "left_semi")


def vote_counts(votes: DataFrame) -> DataFrame:
    """``a, b, n_keep, n_deny`` of ``votes(a, b, verdict, judge)``."""
    return votes.groupBy("a", "b").agg(F.count_if(F.col("verdict") == "keep").alias("n_keep"), F.count_if(F.col("verdict") == "deny").alias("n_deny"))


def verify_votes(pairs: DataFrame, votes: DataFrame, min_votes: int = 2) -> DataFrame:
    """Pairs that a majority of at least ``min_votes`` judges doesn't deny."""
    denied = vote_counts(votes).where((F.col("n_keep") + F.col("n_deny") >= min_votes) & (F.col("n_deny") > F.col("n_keep")))
    return pairs.join(denied.select("a", "b"), ["a", "b"], "left_anti")


def ask_list(pairs: DataFrame, k: int, limit: Column) -> DataFrame:
    """The ``k`` pairs nearest to their threshold: the least sure ones, to be judged by people."""
    return pairs.withColumn("margin", limit - F.col("d")).orderBy("margin", "a", "b").limit(k)


def denied_by_rule(verdicts: DataFrame) -> DataFrame:
    return verdicts.groupBy("rule", "verdict").agg(F.count(F.lit(1)).alias("n"))
