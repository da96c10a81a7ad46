"""The experiment workloads, re-expressed on the trade taxonomy and the catalog."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from unischema.functions.lineage import cut
from unischema.operators import knowledge, metrics
from unischema.operators.components import label_nodes
from unischema.operators.concept import concept_pairs, related_concepts
from unischema.operators.distance import anchor
from unischema.plans.method_queries import MISSPELT_SQL, _PIE_H1_SQL, _components_sql, _concepts, _h1, _misspelt, _pie_h1, reach_sql
from unischema.sources import fixtures, tables
from unischema.sources.taxonomy import H1_SQL

#: Sizes of the fifteen input sets; pairs of one size are drawn sparse first, then dense.
SIZES = [1, 1, 1, 5, 5, 10, 10, 20, 20, 30, 30, 40, 40, 50, 50]
TARGET_SIZES = [1, 5, 10]
THRESHOLD_INPUTS = ["blue anvil", "NATION_0", "BUILDING"]


def ranked(h1: DataFrame) -> DataFrame:
    """Concepts numbered by degree, then name: ``concept, degree, k``.

    Each range partition is numbered by itself, and starts after the sizes of those before it, so that no
    task sees all concepts; the driver reads one number for each partition.
    """
    parted = cut(knowledge.degree(h1).repartitionByRange("degree", "concept").withColumn("part", F.spark_partition_id()))
    sizes = sorted(tuple(r) for r in parted.groupBy("part").count().collect())
    before, total = [], 0
    for part, n in sizes:
        before.append((part, total))
        total += n
    start = F.element_at(F.create_map(*[F.lit(x) for pair in before for x in pair]), F.col("part")) if before else F.lit(0)
    place = F.row_number().over(Window.partitionBy("part").orderBy("degree", "concept"))
    return cut(parted.select("concept", "degree", (place + start).cast("long").alias("k")))


_RANKED_SQL = f"ranked AS (SELECT concept, degree, row_number() OVER (ORDER BY degree, concept) AS k, count(*) OVER () AS n FROM (SELECT concept, count(*) AS degree FROM ({H1_SQL}) GROUP BY concept))"


def size_sets(h1: DataFrame) -> DataFrame:
    """``set_no, concept``: for each size a draw from the middle of the degree order, then from its top."""
    order = ranked(h1)
    n = order.count()
    parts, seen = [], {}
    for number, size in enumerate(SIZES, 1):
        turn = seen[size] = seen.get(size, -1) + 1
        first = n // 2 + 1 + 7 * number if turn == 0 else n - size + 1 - (turn - 1) * 3
        parts.append(order.where((F.col("k") >= first) & (F.col("k") < first + size)).select(F.lit(number).cast("long").alias("set_no"), "concept"))
    return reduce(DataFrame.unionByName, parts)


def _size_sets_sql() -> str:
    parts, seen = [], {}
    for number, size in enumerate(SIZES, 1):
        turn = seen[size] = seen.get(size, -1) + 1
        first = f"n // 2 + 1 + {7 * number}" if turn == 0 else f"n - {size} + 1 - {(turn - 1) * 3}"
        parts.append(f"SELECT {number} AS set_no, concept FROM ranked WHERE k >= {first} AND k < {first} + {size}")
    return " UNION ALL ".join(parts)


def _sizes(sets: DataFrame, h1: DataFrame, gammas: tuple[int, ...], key: str) -> DataFrame:
    """Result and input sizes of each set at each threshold, from one expansion to the largest."""
    sets = cut(sets)
    reached = cut(related_concepts(sets.select("concept").distinct(), h1, max(gammas)))
    met = sets.join(reached, sets["concept"] == reached["start"])
    grid = met.select(key, "concept", "end", F.explode(F.filter(F.array(*map(F.lit, gammas)), lambda g: g >= F.col("len"))).alias("gamma"))
    return grid.groupBy(key, F.col("gamma").cast("long").alias("gamma")).agg(F.count_distinct("concept").alias("input_size"), F.count_distinct("end").alias("result_size"))


def _sizes_sql(sets: str, gammas: tuple[int, ...], key: str, ctes: str = "") -> str:
    values = ", ".join(f"({g})" for g in gammas)
    return f"""WITH RECURSIVE {ctes} sets AS ({sets}), {reach_sql('SELECT DISTINCT concept FROM sets', max(gammas))}
      SELECT {key}, gamma::BIGINT AS gamma, count(DISTINCT concept) AS input_size, count(DISTINCT end_concept) AS result_size
      FROM sets JOIN reach ON concept = start_concept, (VALUES {values}) g(gamma) WHERE hops <= gamma GROUP BY {key}, gamma"""


def result_size_by_size(spark, sf_dir):
    h1 = _h1(spark, sf_dir)
    return _sizes(size_sets(h1), h1, (2, 3), "set_no")


SIZE_SQL = _sizes_sql(_size_sets_sql(), (2, 3), "set_no", _RANKED_SQL + ",")


def target_sets(h1: DataFrame) -> DataFrame:
    """``set_no, concept``: sizes 1, 5 and 10 from the poorest, the middle and the richest third by degree."""
    order = ranked(h1)
    n = order.count()
    parts = []
    for i, size in enumerate(TARGET_SIZES):
        for j, first in enumerate((1, n // 2, n - size + 1)):
            parts.append(order.where((F.col("k") >= first) & (F.col("k") < first + size)).select(F.lit(3 * i + j + 1).cast("long").alias("set_no"), "concept"))
    return reduce(DataFrame.unionByName, parts)


def _target_sql() -> str:
    parts = []
    for i, size in enumerate(TARGET_SIZES):
        for j, first in enumerate(("1", "n // 2", f"n - {size} + 1")):
            parts.append(f"SELECT {3 * i + j + 1} AS set_no, concept FROM ranked WHERE k >= {first} AND k < {first} + {size}")
    return " UNION ALL ".join(parts)


def result_size_by_target(spark, sf_dir):
    h1 = _h1(spark, sf_dir)
    return _sizes(target_sets(h1), h1, (2,), "set_no")


TARGET_SQL = _sizes_sql(_target_sql(), (2,), "set_no", _RANKED_SQL + ",")


def threshold_sets(spark) -> DataFrame:
    rows = [(size, name) for size in (1, 2, 3) for name in THRESHOLD_INPUTS[:size]]
    return fixtures.frame(spark, rows, "set_no long, concept string")


def result_size_by_threshold(spark, sf_dir):
    return _sizes(threshold_sets(spark), _h1(spark, sf_dir), (2, 3, 4), "set_no")


_THRESHOLD_SETS = " UNION ALL ".join(f"SELECT {size} AS set_no, '{name}' AS concept" for size in (1, 2, 3) for name in THRESHOLD_INPUTS[:size])
THRESHOLD_SQL = _sizes_sql(_THRESHOLD_SETS, (2, 3, 4), "set_no")


def threshold_growth(spark, sf_dir):
    return metrics.growth(result_size_by_threshold(spark, sf_dir), "set_no", "gamma", "result_size").select("set_no", "gamma", "ratio")


GROWTH_SQL = f"SELECT set_no, gamma, round(result_size / lag(result_size) OVER (PARTITION BY set_no ORDER BY gamma), 6) AS ratio FROM ({THRESHOLD_SQL})"


def incremental_by_degree(spark, sf_dir):
    """Fifty concepts spread over the degree order: degree and the sizes of their balls at 1, 2 and 3."""
    h1 = _h1(spark, sf_dir)
    order = ranked(h1)
    n = order.count()
    chosen = order.where(F.pmod(F.col("k"), F.lit(n // 50)) == 0)
    sizes = _sizes(chosen.select("concept", F.col("concept").alias("target")), h1, (1, 2, 3), "target")
    return sizes.join(chosen.select(F.col("concept").alias("target"), "degree"), "target").select("target", "degree", "gamma", "result_size")


DEGREE_SQL = f"""SELECT target, degree, gamma, result_size FROM ({_sizes_sql('SELECT concept, concept AS target FROM ranked WHERE k % (n // 50) = 0', (1, 2, 3), 'target', _RANKED_SQL + ',')})
  JOIN (SELECT concept AS target, count(*) AS degree FROM ({H1_SQL}) GROUP BY concept) USING (target)"""


def misspelling_accuracy(spark, sf_dir):
    """Planted misspellings of part names: the anchor found against the name meant."""
    planted = cut(_misspelt(spark, sf_dir))
    found = anchor(planted.select("attr"), _concepts(_h1(spark, sf_dir)), 1).select(F.col("concept").alias("target"), "attr")
    per_target = metrics.accuracy(found, planted.select("target", "attr"))
    return metrics.macro_average(per_target)


MISSPELLING_SQL = f"""WITH gold AS ({MISSPELT_SQL}), found AS (SELECT concept AS target, attr FROM (SELECT DISTINCT attr FROM gold), (SELECT DISTINCT concept FROM ({H1_SQL}))
    WHERE levenshtein(attr, concept) <= 1 QUALIFY rank() OVER (PARTITION BY attr ORDER BY levenshtein(attr, concept)) = 1),
  per AS (SELECT coalesce(f.target, g.target) AS target, count(*) FILTER (WHERE f.attr IS NOT NULL AND g.attr IS NOT NULL) AS common, count(f.attr) AS found, count(g.attr) AS gold
    FROM found f FULL JOIN gold g ON f.target = g.target AND f.attr = g.attr GROUP BY 1)
  SELECT round(avg(CASE WHEN gold > 0 THEN round(common / gold, 6) END), 6) AS recall, round(avg(CASE WHEN found > 0 THEN round(common / found, 6) END), 6) AS precision FROM per"""


def pie_integration(spark, sf_dir):
    """The pastry names of the worked example grouped at threshold 1 and 2."""
    h1 = cut(_pie_h1(spark))
    names = cut(_concepts(h1))
    out = []
    for gamma in (1, 2):
        pairs = concept_pairs(names, h1, gamma)
        out.append(label_nodes(names.select(F.col("concept").alias("node")), pairs).select(F.lit(gamma).cast("long").alias("gamma"), F.col("label").alias("cluster_id"), F.col("node").alias("attr")))
    return out[0].unionByName(out[1])


PIE_SQL = f"SELECT g::BIGINT AS gamma, min(concept) OVER () AS cluster_id, concept AS attr FROM (SELECT DISTINCT concept FROM ({_PIE_H1_SQL})), (VALUES (1), (2)) t(g)"


def nouns_integration(spark, sf_dir):
    """Part names of one noun are within 2 of each other: one cluster for each connected group."""
    h1 = _h1(spark, sf_dir)
    names = cut(tables.table(spark, sf_dir, "part").select(F.col("p_name").alias("concept")).distinct())
    pairs = concept_pairs(names, h1, 2)
    return label_nodes(names.select(F.col("concept").alias("node")), pairs).select(F.col("label").alias("cluster_id"), F.col("node").alias("attr"))


NOUNS_SQL = _components_sql(
    f"SELECT * FROM (WITH RECURSIVE {reach_sql('SELECT DISTINCT p_name AS concept FROM part', 2)} SELECT start_concept AS a, end_concept AS b FROM reach WHERE start_concept < end_concept AND end_concept IN (SELECT p_name FROM part))",
    "SELECT DISTINCT p_name AS attr FROM part",
)


def kb_size_independence(spark, sf_dir):
    """Edges, concepts and the balls of one input: the ball, not the base, decides the work."""
    h1 = _h1(spark, sf_dir)
    seed = fixtures.frame(spark, ["blue anvil"], "concept string")
    reached = related_concepts(seed, h1, 3)
    balls = reached.agg(*[F.count_if(F.col("len") <= g).alias(f"ball_{g}") for g in (1, 2, 3)])
    size = h1.agg(F.count(F.lit(1)).alias("n_rows"), F.count_distinct("concept").alias("n_concepts"))
    return size.crossJoin(balls)


KB_SQL = f"""WITH RECURSIVE {reach_sql("SELECT 'blue anvil' AS concept", 3)}
  SELECT (SELECT count(*) FROM h1) AS n_rows, (SELECT count(DISTINCT concept) FROM h1) AS n_concepts, count(*) FILTER (WHERE hops <= 1) AS ball_1, count(*) FILTER (WHERE hops <= 2) AS ball_2, count(*) AS ball_3 FROM reach"""
