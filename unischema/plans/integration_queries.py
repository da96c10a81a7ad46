"""Verification, resolving, pipelines, measures and experiment workloads as queries."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from unischema.config import DEFAULT
from unischema.functions.lineage import cut
from unischema.operators import clusters, concept, distance, knowledge, layout, literal, metrics, resolve, verify
from unischema.plans import batch, flagship, incremental, workloads
from unischema.plans.method_queries import CATALOG_SQL, NINE_SQL, _catalog_attrs, _components_sql, _concepts, _h1, _nine, _part_names, pairs_sql, reach_sql, register, seeded
from unischema.sources import fixtures, tables
from unischema.sources.fixtures import frame, sql_values
from unischema.sources.taxonomy import H1_SQL

long = lambda df, *names: df.withColumns({n: F.col(n).cast("long") for n in names})
CATALOG = tables.catalog_values()


# ---------------------------------------------------------------- verification

_COLUMNS = {
    "region": "r_regionkey:i r_name:t",
    "nation": "n_nationkey:i n_name:t n_regionkey:i",
    "customer": "c_custkey:i c_name:t c_nationkey:i c_acctbal:f c_mktsegment:t",
    "supplier": "s_suppkey:i s_name:t s_nationkey:i s_acctbal:f",
    "part": "p_partkey:i p_name:t p_brand:t p_type:t p_size:i p_retailprice:f",
    "orders": "o_orderkey:i o_custkey:i o_orderstatus:t o_totalprice:f o_orderdate:d o_orderpriority:t",
    "lineitem": "l_orderkey:i l_partkey:i l_suppkey:i l_linenumber:i l_quantity:f l_extendedprice:f l_discount:f l_tax:f l_returnflag:t l_linestatus:t l_shipdate:d",
    "events": "event_id:i ts:d user_id:i event_type:t value:f props:t",
    "documents": "doc_id:i text:t lang:t source:t n_chars:i",
    "embeddings": "vec_id:i embedding:l label:i",
    "pages": "page_id:i url:t html:t",
    "benchmark": "item_id:i text:t",
    "labels": "doc_id:i quality:i toxic:i",
    "conversations": "conv_id:i turn:i role:t text:t",
}
_LETTERS = {"i": "integer", "f": "fractional", "t": "text", "d": "temporal", "l": "list"}
_CELLS = [(name, *cell.split(":")) for name, columns in _COLUMNS.items() for cell in columns.split()]
#: The catalog with families as plain rows: SQL forms must not lean on the connection's own catalog.
_OWN_SQL = f"SELECT * FROM {sql_values([(t, c, _LETTERS[k], 'fractional' if k == 'l' else '') for t, c, k in _CELLS], 'schema_id', 'attr', 'family', 'element')}"


def _profile_sql(distinct: bool = False) -> str:
    rows = []
    for name, column, kind in _CELLS:
        affix = lambda f, c=column: f"CASE WHEN min({f}({c}, 3)) = max({f}({c}, 3)) THEN min({f}({c}, 3)) END"
        prefix, suffix = (affix("left"), affix("right")) if kind == "t" else ("NULL::VARCHAR", "NULL::VARCHAR")
        more = f", count(DISTINCT {column}) AS n_distinct" if distinct else ""
        rows.append(f"SELECT '{name}' AS schema_id, '{column}' AS attr, '{_LETTERS[kind]}' AS family, {prefix} AS prefix, {suffix} AS suffix, count({column}) AS n_values{more} FROM {name}")
    return " UNION ALL ".join(rows)


def _profile(spark, sf_dir) -> DataFrame:
    return cut(verify.profile_values(_all_tables(spark, sf_dir)))


def _all_tables(spark, sf_dir) -> dict[str, DataFrame]:
    return {t: tables.table(spark, sf_dir, t) for t in tables.TABLES}


@register(_profile_sql(distinct=True))
def value_profile(spark, sf_dir):
    return verify.profile_values(_all_tables(spark, sf_dir), distinct=True).drop("element_family")


_SUPPORT = 0.6
_SUPPORT_SQL = " UNION ALL ".join(
    f"SELECT '{t}' AS schema_id, '{c}' AS attr, '{side}' AS side, arg_min(affix, (-n, affix)) AS affix, round(max(n) / sum(n), 6) AS support FROM (SELECT {f}({c}, 3) AS affix, count(*) AS n FROM {t} WHERE {c} IS NOT NULL GROUP BY 1) HAVING sum(n) > 0 AND round(max(n) / sum(n), 6) >= {_SUPPORT}"
    for t, c, k in _CELLS if k == "t" for side, f in (("prefix", "left"), ("suffix", "right"))
)


@register(_SUPPORT_SQL)
def affix_support(spark, sf_dir):
    """Affixes that at least 60 % of a text column's values share."""
    return verify.affix_support(_all_tables(spark, sf_dir), _SUPPORT)


def _near_pairs(spark, sf_dir, eps: int = 2) -> DataFrame:
    """Occurrence pairs (schema, name) of all tables with names within ``eps``."""
    own = cut(_catalog_attrs(spark, sf_dir))
    pairs = literal.literal_pairs(own, eps).select("a", "b")
    x, y = own.select(F.col("schema_id").alias("schema_a"), F.col("attr").alias("a")), own.select(F.col("schema_id").alias("schema_b"), F.col("attr").alias("b"))
    return cut(pairs.join(x, "a").join(y, "b").select("schema_a", "a", "schema_b", "b"))


_NEAR_SQL = f"""own AS MATERIALIZED ({_OWN_SQL}), prof AS MATERIALIZED ({_profile_sql()}),
  pairs AS MATERIALIZED (SELECT x.schema_id AS schema_a, x.attr AS a, y.schema_id AS schema_b, y.attr AS b, x.family AS fa, y.family AS fb, x.element AS ea, y.element AS eb
    FROM own x JOIN own y ON x.attr < y.attr AND levenshtein(x.attr, y.attr) <= 2),
  wide AS MATERIALIZED (SELECT pairs.*, p.prefix AS pa, q.prefix AS pb, p.suffix AS sa, q.suffix AS sb, p.n_values AS na, q.n_values AS nb FROM pairs
    JOIN prof p ON p.schema_id = schema_a AND p.attr = a JOIN prof q ON q.schema_id = schema_b AND q.attr = b)"""
_TYPE_SQL = "CASE WHEN na = 0 OR nb = 0 THEN 'unknown' WHEN fa = fb THEN 'keep' ELSE 'deny' END"
_STRUCTURE_SQL = "CASE WHEN fa <> 'list' AND fb <> 'list' THEN 'unknown' WHEN fa = fb AND ea = eb THEN 'keep' ELSE 'deny' END"
_AFFIX_SQL = "CASE WHEN (pa IS NULL OR pb IS NULL) AND (sa IS NULL OR sb IS NULL) THEN 'unknown' WHEN coalesce(pa = pb, false) OR coalesce(sa = sb, false) THEN 'keep' ELSE 'deny' END"


def _rule_query(name: str, verdict: str, rule) -> None:
    @register(f"WITH {_NEAR_SQL} SELECT schema_a, a, schema_b, b, '{name}' AS rule, {verdict} AS verdict FROM wide", name=f"rule_{name}" if name != "structure" else "rule_structure_catalog")
    def query(spark, sf_dir):
        return rule(_near_pairs(spark, sf_dir), _profile(spark, sf_dir))


_rule_query("type", _TYPE_SQL, verify.rule_type)
_rule_query("affix", _AFFIX_SQL, verify.rule_affix)
_rule_query("structure", _STRUCTURE_SQL, verify.rule_structure)


@register(f"""WITH {_NEAR_SQL}, sup AS MATERIALIZED ({_SUPPORT_SQL}),
  met AS (SELECT w.schema_a, w.a, w.schema_b, w.b, p.affix AS pa, q.affix AS pb, s.affix AS sa, t.affix AS sb FROM wide w
    LEFT JOIN sup p ON p.schema_id = schema_a AND p.attr = a AND p.side = 'prefix' LEFT JOIN sup q ON q.schema_id = schema_b AND q.attr = b AND q.side = 'prefix'
    LEFT JOIN sup s ON s.schema_id = schema_a AND s.attr = a AND s.side = 'suffix' LEFT JOIN sup t ON t.schema_id = schema_b AND t.attr = b AND t.side = 'suffix')
  SELECT schema_a, a, schema_b, b, 'affix' AS rule, {_AFFIX_SQL} AS verdict FROM met""")
def rule_affix_supported(spark, sf_dir):
    """The affix rule on affixes with a support of 60 %."""
    support = verify.affix_support(_all_tables(spark, sf_dir), _SUPPORT)
    return verify.rule_affix(_near_pairs(spark, sf_dir), verify.with_affixes(_profile(spark, sf_dir), support))


@register("SELECT * FROM (VALUES ('list', 'unknown', 1), ('list', 'keep', 1), ('list', 'deny', 1)) t(kind, verdict, n)")
def rule_structure(spark, sf_dir):
    profile = frame(spark, [("s", "a", "list", "integer"), ("s", "b", "list", "integer"), ("s", "c", "list", "text"), ("s", "d", "text", None), ("s", "e", "text", None)], "schema_id string, attr string, family string, element_family string")
    profile = profile.withColumns({"prefix": F.lit(None).cast("string"), "suffix": F.lit(None).cast("string"), "n_values": F.lit(1)})
    pairs = frame(spark, [("s", "a", "s", "b"), ("s", "a", "s", "c"), ("s", "d", "s", "e")], "schema_a string, a string, schema_b string, b string")
    return verify.rule_structure(pairs, profile).groupBy(F.lit("list").alias("kind"), "verdict").agg(F.count(F.lit(1)).alias("n"))


_KEPT_SQL = f"SELECT schema_a, a, schema_b, b FROM wide WHERE {_TYPE_SQL} <> 'deny' AND {_STRUCTURE_SQL} <> 'deny'"


@register(f"WITH {_NEAR_SQL} {_KEPT_SQL}")
def verified_pairs(spark, sf_dir):
    return verify.verify_values(_near_pairs(spark, sf_dir), _profile(spark, sf_dir))[0]


@register(f"WITH {_NEAR_SQL} SELECT DISTINCT a, b FROM ({_KEPT_SQL})")
def verified_names(spark, sf_dir):
    """Name pairs of which some occurrences may be the same: one comparison for each kind of profile."""
    pairs = _near_pairs(spark, sf_dir).select("a", "b").distinct()
    return verify.verify_names(pairs, _catalog_attrs(spark, sf_dir), _profile(spark, sf_dir))


def _rule_key(pairs, profile):
    """A rule of one's own: names that end in ``key`` match only names that do."""
    ends = lambda c: F.endswith(F.col(c), F.lit("key"))
    verdict = F.when(ends("a") == ends("b"), "keep").otherwise("deny")
    return pairs.select("schema_a", "a", "schema_b", "b", F.lit("key").alias("rule"), verdict.alias("verdict"))


@register(f"WITH {_NEAR_SQL} SELECT schema_a, a, schema_b, b FROM ({_KEPT_SQL}) WHERE ends_with(a, 'key') = ends_with(b, 'key')")
def verified_with_own_rule(spark, sf_dir):
    """The hook for more rules: a function of pairs and profile beside the given ones."""
    return verify.verify_values(_near_pairs(spark, sf_dir), _profile(spark, sf_dir), (verify.rule_type, verify.rule_structure, _rule_key))[0]


@register(f"WITH {_NEAR_SQL} SELECT 'type' AS rule, {_TYPE_SQL} AS verdict, count(*) AS n FROM wide GROUP BY ALL UNION ALL SELECT 'affix', {_AFFIX_SQL}, count(*) FROM wide GROUP BY ALL")
def denied_by_rule(spark, sf_dir):
    pairs, profile = _near_pairs(spark, sf_dir), _profile(spark, sf_dir)
    return verify.denied_by_rule(verify.rule_type(pairs, profile).unionByName(verify.rule_affix(pairs, profile)))


_KEY_PAIRS = [("orders", "o_custkey", "customer", "c_custkey"), ("lineitem", "l_orderkey", "orders", "o_orderkey"), ("lineitem", "l_partkey", "part", "p_partkey"), ("nation", "n_regionkey", "region", "r_regionkey"), ("part", "p_size", "part", "p_partkey"), ("labels", "doc_id", "documents", "doc_id"), ("customer", "c_name", "supplier", "s_name")]
_CONTAINMENT_SQL = " UNION ALL ".join(
    f"SELECT '{s}' AS schema_a, '{a}' AS a, '{t}' AS schema_b, '{b}' AS b, 'containment' AS rule, CASE WHEN NOT EXISTS (SELECT {a} FROM {s} WHERE {a} NOT IN (SELECT {b} FROM {t})) OR NOT EXISTS (SELECT {b} FROM {t} WHERE {b} NOT IN (SELECT {a} FROM {s})) THEN 'keep' ELSE 'unknown' END AS verdict"
    for s, a, t, b in _KEY_PAIRS
)


@register(_CONTAINMENT_SQL)
def rule_containment(spark, sf_dir):
    pairs = frame(spark, _KEY_PAIRS, "schema_a string, a string, schema_b string, b string")
    wanted: dict[str, list[str]] = {}
    for s, a, t, b in _KEY_PAIRS:
        wanted.setdefault(s, []).append(a)
        wanted.setdefault(t, []).append(b)
    return verify.rule_containment(pairs, verify.unpivot_values(_all_tables(spark, sf_dir), wanted))


_VOTES_SQL = f"SELECT * FROM {sql_values(fixtures.VOTES, 'a', 'b', 'verdict', 'judge')}"


def _votes(spark):
    return frame(spark, fixtures.VOTES, "a string, b string, verdict string, judge string")


@register(f"SELECT a, b, count(*) FILTER (WHERE verdict = 'keep') AS n_keep, count(*) FILTER (WHERE verdict = 'deny') AS n_deny FROM ({_VOTES_SQL}) GROUP BY ALL")
def vote_counts(spark, sf_dir):
    return verify.vote_counts(_votes(spark))


@register(f"""SELECT a, b FROM ({pairs_sql(CATALOG_SQL, 2)}) p WHERE NOT EXISTS (SELECT 1 FROM ({_VOTES_SQL}) v WHERE v.a = p.a AND v.b = p.b
  HAVING count(*) >= 2 AND count(*) FILTER (WHERE verdict = 'deny') > count(*) FILTER (WHERE verdict = 'keep'))""")
def votes_verdict(spark, sf_dir):
    pairs = literal.literal_pairs(_catalog_attrs(spark, sf_dir), 2).select("a", "b")
    return verify.verify_votes(pairs, _votes(spark))


@register(f"SELECT a, b, d, 2 - d AS margin FROM ({pairs_sql(CATALOG_SQL, 2)}) ORDER BY margin, a, b LIMIT 5")
def ask_list(spark, sf_dir):
    pairs = literal.literal_pairs(_catalog_attrs(spark, sf_dir), 2)
    return long(verify.ask_list(pairs, 5, F.lit(2)), "d", "margin")


# ---------------------------------------------------------------- resolving


def _chain(spark, rows):
    pairs = frame(spark, rows, "a string, b string")
    nodes = pairs.select(F.col("a").alias("attr")).union(pairs.select("b")).distinct()
    return nodes.select(F.lit("c").alias("cluster_id"), "attr"), pairs


_CHAIN_NEAR = [*fixtures.CHAIN, ("xa", "xj"), ("xi", "xb")]


_PARTS_SQL = "SELECT DISTINCT p_name AS attr FROM part"
_SHARED_SQL = "WITH w AS (SELECT attr, unnest(string_split(attr, ' ')) AS word FROM (SELECT DISTINCT p_name AS attr FROM part)) SELECT DISTINCT x.attr AS a, y.attr AS b FROM w x JOIN w y ON x.word = y.word AND x.attr < y.attr"


@register(f"""WITH m AS MATERIALIZED ({_components_sql(_SHARED_SQL, _PARTS_SQL)}), near AS MATERIALIZED ({_SHARED_SQL})
  SELECT x.cluster_id, x.attr AS a, y.attr AS b FROM m x JOIN m y ON x.cluster_id = y.cluster_id AND x.attr < y.attr WHERE NOT EXISTS (SELECT 1 FROM near WHERE near.a = x.attr AND near.b = y.attr)""")
def conflict_pairs(spark, sf_dir):
    """Part names that share a word are near, and chain into clusters; pairs of a cluster that share none."""
    names = cut(_part_names(spark, sf_dir).select(F.col("concept").alias("attr")).where("attr IS NOT NULL"))
    words = cut(names.select("attr", F.explode(F.split("attr", " ")).alias("word")))
    x, y = words.alias("x"), words.alias("y")
    shared = x.join(y, F.col("x.word") == F.col("y.word")).where("x.attr < y.attr").select(F.col("x.attr").alias("a"), F.col("y.attr").alias("b"))
    near = cut(shared.distinct())
    return resolve.conflicts(clusters_of(names, near), near)


@register("SELECT * FROM (VALUES ('xa|xi|xj', 'xa'), ('xa|xi|xj', 'xi'), ('xa|xi|xj', 'xj'), ('xb|xi|xj', 'xb'), ('xb|xi|xj', 'xi'), ('xb|xi|xj', 'xj')) t(part_id, attr)")
def resolve_overlap_chain(spark, sf_dir):
    members, near = _chain(spark, _CHAIN_NEAR)
    return resolve.resolve_overlap(members, near).select("part_id", "attr")


@register("SELECT * FROM (VALUES ('building|house', 'building'), ('building|house', 'house'), ('home|house', 'home'), ('home|house', 'house'), ('family|home', 'family'), ('family|home', 'home')) t(part_id, attr)")
def resolve_home_closure(spark, sf_dir):
    members, near = _chain(spark, fixtures.HOME_CHAIN)
    return resolve.resolve_overlap(members, near).select("part_id", "attr")


@register("SELECT * FROM (VALUES ('c', 'c/0', 'building'), ('c', 'c/0', 'house'), ('c', 'c/1', 'family'), ('c', 'c/1', 'home')) t(cluster_id, part_id, attr)")
def resolve_dense_home(spark, sf_dir):
    members, near = _chain(spark, fixtures.HOME_CHAIN)
    return resolve.resolve_dense(members, near)


@register()
def resolve_cover_tokens(spark, sf_dir):
    """Ball cover of the giant chains of similar tokens: radius 1 for a tolerance of 2."""
    tokens = cut(tables.all_tokens(spark, sf_dir))
    pairs = cut(literal.literal_pairs(tokens, 1))
    members = cut(clusters_of(tokens, pairs))
    return resolve.resolve_cover(members, pairs.select("a", "b"))


@register("SELECT 0::BIGINT AS n_far_pairs, 0::BIGINT AS n_uncovered")
def resolve_cover_violations(spark, sf_dir):
    """Of the ball cover: pairs in a part beyond the tolerance, and members in no part; both none."""
    tokens = cut(tables.all_tokens(spark, sf_dir))
    pairs = cut(literal.literal_pairs(tokens, 1))
    members = cut(clusters_of(tokens, pairs))
    parts = cut(resolve.resolve_cover(members, pairs.select("a", "b")))
    x, y = parts.alias("x"), parts.alias("y")
    far = x.join(y, (F.col("x.part_id") == F.col("y.part_id")) & (F.col("x.attr") < F.col("y.attr"))).where(F.levenshtein("x.attr", "y.attr") > 2)
    lost = members.join(parts, ["cluster_id", "attr"], "left_anti")
    return far.agg(F.count(F.lit(1)).alias("n_far_pairs")).crossJoin(lost.agg(F.count(F.lit(1)).alias("n_uncovered")))


def clusters_of(attrs, pairs):
    from unischema.operators.components import label_nodes

    labels = label_nodes(attrs.select(F.col("attr").alias("node")), pairs.select("a", "b"))
    return labels.select(F.col("label").alias("cluster_id"), F.col("node").alias("attr"))


@register(f"""SELECT count(DISTINCT cluster_id) AS n_clusters, count(*) AS n_members, max(n)::BIGINT AS largest, 0::BIGINT AS n_overlapping
  FROM (SELECT *, count(*) OVER (PARTITION BY cluster_id) AS n FROM ({_components_sql(pairs_sql(CATALOG_SQL, 1), CATALOG_SQL)}))""")
def cluster_stats(spark, sf_dir):
    return long(clusters.cluster_stats(literal.self_literal_clusters(_catalog_attrs(spark, sf_dir), 1)), "n_members", "largest", "n_clusters", "n_overlapping")


# ---------------------------------------------------------------- batch

_CATALOG_MEMBERS = _components_sql(pairs_sql(CATALOG_SQL, 1), CATALOG_SQL)


@register(_CATALOG_MEMBERS)
def batch_catalog_clusters(spark, sf_dir):
    return flagship.catalog_integration(spark, sf_dir).members


_MAPPING_SQL = f"""WITH members AS ({_CATALOG_MEMBERS}), pooled AS (SELECT attr, count(DISTINCT schema_id) AS n FROM {CATALOG} GROUP BY attr),
  best AS (SELECT cluster_id, attr AS global_attr FROM members JOIN pooled USING (attr) QUALIFY row_number() OVER (PARTITION BY cluster_id ORDER BY n DESC, length(attr), attr DESC) = 1)
  SELECT DISTINCT schema_id, c.attr, global_attr FROM {CATALOG} c JOIN members m ON c.attr = m.attr JOIN best USING (cluster_id)"""


@register(_MAPPING_SQL)
def batch_catalog_mapping(spark, sf_dir):
    return flagship.catalog_integration(spark, sf_dir).mapping.select("schema_id", "attr", "global_attr")


@register(f"WITH m AS ({_MAPPING_SQL}) SELECT global_attr, count(DISTINCT attr) AS size FROM m GROUP BY global_attr")
def representatives(spark, sf_dir):
    return flagship.catalog_integration(spark, sf_dir, with_values=False).global_schema.select("global_attr", "size")


@register("SELECT 0::BIGINT AS n_violations")
def coverage_violations(spark, sf_dir):
    done = flagship.catalog_integration(spark, sf_dir, with_values=False)
    near = literal.literal_pairs(_catalog_attrs(spark, sf_dir), 1).select("a", "b")
    return resolve.coverage_violations(done.mapping, _catalog_attrs(spark, sf_dir), near).agg(F.count(F.lit(1)).alias("n_violations"))


@register(f"WITH m AS ({_MAPPING_SQL}) SELECT count(DISTINCT attr) AS n_attrs, count(DISTINCT global_attr) AS n_global, round(count(DISTINCT attr) / count(DISTINCT global_attr), 6) AS ratio FROM m")
def compression(spark, sf_dir):
    done = flagship.catalog_integration(spark, sf_dir, with_values=False)
    return metrics.compression(_catalog_attrs(spark, sf_dir), done.global_schema)


def _nine_schema(spark, sf_dir):
    return cut(_nine(spark, sf_dir).select(F.concat(F.lit("s"), F.substring("concept", 1, 4)).alias("schema_id"), F.col("concept").alias("attr")))


_NINE_PAIRS = f"WITH RECURSIVE {reach_sql(NINE_SQL, 2)} SELECT start_concept AS a, end_concept AS b FROM reach WHERE start_concept < end_concept AND end_concept IN (SELECT concept FROM seeds)"


def _all_schema(spark, sf_dir):
    """Every part name, each in the schema of its first letters."""
    return cut(_part_names(spark, sf_dir).select(F.concat(F.lit("s"), F.substring("concept", 1, 4)).alias("schema_id"), F.col("concept").alias("attr")))


_ALL_PAIRS = f"WITH RECURSIVE {reach_sql('SELECT DISTINCT p_name AS concept FROM part', 2)} SELECT start_concept AS a, end_concept AS b FROM reach WHERE start_concept < end_concept AND end_concept IN (SELECT concept FROM seeds)"


@register(_components_sql(_ALL_PAIRS, "SELECT DISTINCT p_name AS attr FROM part"))
def batch_taxonomy_all(spark, sf_dir):
    """Semantic integration of all part names at threshold 2: clusters."""
    return batch.integrate_batch(_all_schema(spark, sf_dir), _h1(spark, sf_dir), DEFAULT.but(gamma=2, literal=False, resolve="none")).members


@register(_components_sql(_NINE_PAIRS, f"SELECT concept AS attr FROM ({NINE_SQL})"))
def batch_taxonomy(spark, sf_dir):
    """Semantic integration of nine names at threshold 2: clusters."""
    return batch.integrate_batch(_nine_schema(spark, sf_dir), _h1(spark, sf_dir), DEFAULT.but(gamma=2, literal=False, resolve="none")).members


@register(f"WITH RECURSIVE {reach_sql(NINE_SQL, 2)} SELECT count(DISTINCT start_concept) AS input_size, count(DISTINCT end_concept) AS result_size FROM reach")
def batch_case_study(spark, sf_dir):
    """The case study: nine related names, threshold 2, how many concepts are in the result."""
    done = batch.integrate_batch(_nine_schema(spark, sf_dir), _h1(spark, sf_dir), DEFAULT.but(gamma=2, literal=False, resolve="none"))
    return metrics.result_size(done.related)


@register(f"SELECT a, b FROM ({pairs_sql(CATALOG_SQL, 1)})")
def batch_literal_only(spark, sf_dir):
    return batch.integrate_batch(_catalog_attrs(spark, sf_dir), None, DEFAULT.but(semantic=False, resolve="none")).pairs.select("a", "b")


for _strategy in ("overlap", "cover", "dense"):

    @register(name=f"batch_all_{_strategy}")
    def _resolved_all(spark, sf_dir, strategy=_strategy):
        return batch.integrate_batch(_all_schema(spark, sf_dir), _h1(spark, sf_dir), DEFAULT.but(gamma=2, literal=False, resolve=strategy)).parts

    if _strategy != "overlap":

        @register(name=f"batch_nine_{_strategy}")
        def _resolved(spark, sf_dir, strategy=_strategy):
            return batch.integrate_batch(_nine_schema(spark, sf_dir), _h1(spark, sf_dir), DEFAULT.but(gamma=2, literal=False, resolve=strategy)).parts


@register()
def batch_closure_beta_one_all(spark, sf_dir):
    return batch.integrate_batch(_all_schema(spark, sf_dir), _h1(spark, sf_dir), DEFAULT.but(gamma=2, literal=False, beta=1.0)).parts


@register(f"""WITH near AS MATERIALIZED ({_ALL_PAIRS}) SELECT a, b FROM ({pairs_sql("SELECT DISTINCT p_name AS attr FROM part", 1)}) p WHERE NOT EXISTS (SELECT 1 FROM near WHERE near.a = p.a AND near.b = p.b)""")
def rule_disagreements(spark, sf_dir):
    """Pairs joined by the pipeline at (1, 2) that the two-case rule does not call related."""
    h1 = _h1(spark, sf_dir)
    names = tables.table(spark, sf_dir, "part").select(F.lit("s").alias("schema_id"), F.col("p_name").alias("attr")).distinct()
    cfg = DEFAULT.but(gamma=2, resolve="none")
    return batch.rule_disagreements(batch.integrate_batch(names, h1, cfg).pairs, _concepts(h1), h1, cfg)


@seeded(lambda seeds: f"""WITH RECURSIVE {reach_sql(seeds, 4)}, s AS (SELECT start_concept, g, count(*) AS n FROM reach, range(0, 5) t(g) WHERE hops <= g GROUP BY ALL)
  SELECT start_concept AS concept, max(g)::BIGINT AS gamma, max(n)::BIGINT AS n FROM s WHERE n <= 500 GROUP BY start_concept""")
def advise_gamma(spark, sf_dir, seeds):
    return long(batch.advise_gamma(seeds, _h1(spark, sf_dir), 500), "gamma", "n")


# ---------------------------------------------------------------- incremental

_STEPS = DEFAULT.but(gamma=2, resolve="none")


def _arrivals(spark, sf_dir):
    rows = _nine_schema(spark, sf_dir)
    names = sorted(r["attr"] for r in rows.collect())
    return [frame(spark, [(f"arrival{i}", name)], "schema_id string, attr string") for i, name in enumerate(names)]


def _all_arrivals(spark, sf_dir):
    """Every part name, one arrival for each schema of ``_all_schema``."""
    arrivals: dict[str, list[tuple[str, str]]] = {}
    for r in sorted(_all_schema(spark, sf_dir).collect()):
        arrivals.setdefault(r["schema_id"], []).append(tuple(r))
    return [frame(spark, rows, "schema_id string, attr string") for rows in arrivals.values()]


@register("SELECT 0::BIGINT AS n_new")
def incremental_replay(spark, sf_dir):
    """The same nine again, as one arrival: none is inserted."""
    h1 = _h1(spark, sf_dir)
    once = incremental.integrate_many(incremental.State.empty(spark), _arrivals(spark, sf_dir), h1, _STEPS)
    again = incremental.integrate_one(incremental.State(once.member, once.halo, once.mapping.limit(0)), _nine_schema(spark, sf_dir), h1, _STEPS)
    return again.mapping.where("how = 'new'").agg(F.count(F.lit(1)).alias("n_new"))


@register(f"""WITH RECURSIVE {reach_sql(f'SELECT concept FROM ({NINE_SQL}) ORDER BY concept LIMIT 1', 2)}
  SELECT DISTINCT p_name AS attr FROM part JOIN reach ON p_name = end_concept""")
def halo_hits(spark, sf_dir):
    """Part names that hit the halo or the member of one kept name, found without any expansion."""
    h1 = _h1(spark, sf_dir)
    first = _arrivals(spark, sf_dir)[0]
    state = incremental.integrate_one(incremental.State.empty(spark), first, h1, _STEPS.but(eps_t=0))
    names = tables.table(spark, sf_dir, "part").select(F.col("p_name").alias("attr")).distinct()
    return incremental.halo_hits(names, state, _STEPS.but(eps_t=0)).select("attr").distinct()


@seeded(lambda seeds: f"""SELECT cluster_id, concept FROM (SELECT n.concept AS cluster_id, h.neighbour AS concept, row_number() OVER (PARTITION BY n.concept ORDER BY d.degree DESC, h.neighbour) AS k
  FROM ({seeds}) n JOIN ({H1_SQL}) h ON n.concept = h.concept JOIN (SELECT concept, count(*) AS degree FROM ({H1_SQL}) GROUP BY concept) d ON h.neighbour = d.concept) WHERE k <= 4""")
def halo_top_degree(spark, sf_dir, seeds):
    members = seeds.select(F.col("concept").alias("cluster_id"), F.col("concept").alias("attr"))
    return concept.ball_halo(members, _h1(spark, sf_dir), 2, "top_degree", 4).select("cluster_id", "concept")


def _policy_counts(spark, sf_dir, arrivals, policy):
    done = incremental.integrate_many(incremental.State.empty(spark), arrivals, _h1(spark, sf_dir), _STEPS.but(halo_policy=policy))
    counts = done.mapping.groupBy("how").agg(F.count(F.lit(1)).alias("n"))
    return counts.crossJoin(done.halo.agg(F.count(F.lit(1)).alias("halo_rows")))


for _policy in ("ball", "top_degree", "none"):

    @register(name=f"incremental_policy_{_policy}_all")
    def _policies_all(spark, sf_dir, policy=_policy):
        """How many of all part names are new, and how large the halo grows, by halo policy."""
        return _policy_counts(spark, sf_dir, _all_arrivals(spark, sf_dir), policy)


# ---------------------------------------------------------------- measures

@register(f"SELECT word, round(common / gold, 6) AS recall, round(common / found, 6) AS precision FROM {sql_values(fixtures.PUBLISHED, 'word', 'found', 'gold', 'common', 'r', 'p')}")
def published_ratios(spark, sf_dir):
    rows = frame(spark, fixtures.PUBLISHED, "word string, found int, gold int, common int, r double, p double")
    return rows.select("word", F.round(F.col("common") / F.col("gold"), 6).alias("recall"), F.round(F.col("common") / F.col("found"), 6).alias("precision"))


@seeded(lambda seeds: f"""WITH RECURSIVE {reach_sql(seeds, 3)} SELECT hops, count(*) AS n_paths, count(DISTINCT end_concept) AS n_ends FROM reach GROUP BY hops""")
def frontier_stats(spark, sf_dir, seeds):
    stats = metrics.frontier_stats(knowledge.k_hop(seeds, _h1(spark, sf_dir), 3))
    return stats.select(F.col("len").cast("long").alias("hops"), "n_paths", "n_ends")


@register(f"WITH RECURSIVE {reach_sql('SELECT n_name AS concept FROM nation', 2)} SELECT start_concept AS concept, count(*) AS degree2 FROM reach WHERE hops = 2 GROUP BY 1")
def second_degree(spark, sf_dir):
    seeds = tables.table(spark, sf_dir, "nation").select(F.col("n_name").alias("concept"))
    return metrics.second_degree(seeds, _h1(spark, sf_dir))


_KEPT_GOLD = [("c_custkey", "o_custkey"), ("c_name", "s_name")]


@register(f"""SELECT round(avg(r), 6) AS mean, round(stddev_samp(r), 6) AS deviation FROM (SELECT judge, count(*) FILTER (WHERE verdict = 'keep' AND (a, b) IN (('c_custkey', 'o_custkey'), ('c_name', 's_name'))) / 2 AS r FROM ({_VOTES_SQL}) GROUP BY judge)""")
def judge_agreement(spark, sf_dir):
    return metrics.judge_agreement(_votes(spark), frame(spark, _KEPT_GOLD, "a string, b string"))


# ---------------------------------------------------------------- layout


def _address_sql(attrs: str) -> str:
    return f"""SELECT attr, 1000000 + (((CASE WHEN h >= 2147483648 THEN h - 4294967296 ELSE h END) % 10000) + 10000) % 10000 AS address
  FROM (SELECT attr, list_reduce(list_prepend(0::BIGINT, list_transform(string_split(attr, ''), lambda c : ascii(c)::BIGINT)), lambda k, c : (k * 13 + c) % 4294967296) AS h FROM ({attrs}))"""


@register(f"SELECT attr, address - 1000000 AS offset_in_bucket, address FROM ({_address_sql('SELECT DISTINCT c_name AS attr FROM customer WHERE c_name IS NOT NULL')})")
def bucket_address(spark, sf_dir):
    """Addresses of all names of customers."""
    names = tables.table(spark, sf_dir, "customer").select(F.col("c_name").alias("attr")).where("attr IS NOT NULL").distinct()
    return layout.addresses(names).select("attr", F.col("offset").alias("offset_in_bucket"), "address")


@register(f"""SELECT attr, 1000000 + (((CASE WHEN h >= 2147483648 THEN h - 4294967296 ELSE h END) % 10000) + 10000) % 10000 AS address
  FROM (SELECT attr, list_reduce(list_prepend(0::BIGINT, list_transform(string_split(attr, ''), lambda c : ascii(c)::BIGINT)), lambda k, c : (k * 13 + c) % 4294967296) AS h FROM ({CATALOG_SQL}))""")
def bucket_address_catalog(spark, sf_dir):
    return layout.addresses(_catalog_attrs(spark, sf_dir).select("attr").distinct()).select("attr", "address")


@register(f"SELECT count(DISTINCT cluster_id) AS n_buckets, count(*) AS n_rows FROM ({_CATALOG_MEMBERS})")
def assigned_buckets(spark, sf_dir):
    placed = layout.assign_buckets(literal.self_literal_clusters(_catalog_attrs(spark, sf_dir), 1))
    return placed.agg(F.count_distinct("bucket").alias("n_buckets"), F.count(F.lit(1)).alias("n_rows"))


# ---------------------------------------------------------------- workloads


def _workload(name, function, sql):
    register(sql, name=name)(function)


_workload("result_size_by_size", workloads.result_size_by_size, workloads.SIZE_SQL)
_workload("result_size_by_target", workloads.result_size_by_target, workloads.TARGET_SQL)
_workload("result_size_by_threshold", workloads.result_size_by_threshold, workloads.THRESHOLD_SQL)
_workload("threshold_growth", workloads.threshold_growth, workloads.GROWTH_SQL)
_workload("incremental_by_degree", workloads.incremental_by_degree, workloads.DEGREE_SQL)
_workload("misspelling_accuracy", workloads.misspelling_accuracy, workloads.MISSPELLING_SQL)
_workload("pie_integration", workloads.pie_integration, workloads.PIE_SQL)
_workload("nouns_integration", workloads.nouns_integration, workloads.NOUNS_SQL)
_workload("kb_size_independence", workloads.kb_size_independence, workloads.KB_SQL)
