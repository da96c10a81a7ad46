"""Name normalisation: identity, abbreviations, word cutting, patterns; and the choice of a key word."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from unischema.functions.lineage import cut

#: Patterns of the last rule, tried in order: regex on the whole lower-case name, and its concept.
PATTERNS = [
    (r"^(jan|feb|mar|apr|may|jun|jul|aug|sep|oct|nov|dec)-[0-9]{1,2}$", "date"),
    (r"^[0-9]{4}-[0-9]{1,2}(-[0-9]{1,2})?$", "date"),
    (r"^q[1-4]-[0-9]{2,4}$", "quarter"),
]


def split_words(attr: Column) -> Column:
    """Lower-case words by camel case, underscores, blanks and hyphens."""
    spaced = F.regexp_replace(attr, "([a-z0-9])([A-Z])", "$1 $2")
    return F.filter(F.split(F.lower(spaced), r"[_\s-]+"), lambda w: w != "")


def _words(attrs: DataFrame) -> DataFrame:
    names = attrs.select("attr").where("attr IS NOT NULL").distinct()
    return names.select("attr", F.posexplode(split_words(F.col("attr"))).alias("at", "word"))


def _regroup(rows: DataFrame, word: str) -> DataFrame:
    """Words in their order again: ``attr, words``."""
    return rows.groupBy("attr").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("at", word))), lambda x: x[word]), " ").alias("words"))


def rule_identity(attrs: DataFrame, vocab: DataFrame) -> DataFrame:
    """Names that are dictionary words already: ``attr, words``."""
    names = attrs.select("attr").where("attr IS NOT NULL").distinct().withColumn("word", F.lower("attr"))
    return names.join(vocab.select("word").distinct(), "word", "left_semi").select("attr", F.col("word").alias("words"))


def rule_abbreviation(attrs: DataFrame, abbreviations: DataFrame) -> DataFrame:
    """Names with a known short form in them, expanded; from descriptions or a common list."""
    rows = _words(attrs).join(abbreviations.select(F.col("short").alias("word"), "full"), "word", "left")
    hit = rows.where("full IS NOT NULL").select("attr").distinct()
    return _regroup(rows.join(hit, "attr", "left_semi").withColumn("long", F.coalesce("full", "word")), "long")


def compound_cuts(words: DataFrame, vocab: DataFrame, parts: int = 2) -> DataFrame:
    """``word, split``: words made of up to ``parts`` dictionary words of two letters or more each.

    Of several cuts the one with the longest first part wins, then with the longest second one, and so on.
    Each round cuts one more part off what is left, and goes on with rests that are long enough.
    """
    dictionary = vocab.select("word").distinct()
    rest = words.select("word", F.lit("").alias("done"), F.array().cast("array<int>").alias("sizes"), F.col("word").alias("rest"))
    found = None
    for _ in range(parts - 1):
        long = rest.where(F.length("rest") >= 4)
        places = F.transform(F.sequence(F.lit(2), F.length("rest") - 2), lambda i: F.struct(i.alias("at"), F.substring("rest", F.lit(1), i).alias("head"), F.substring(F.col("rest"), i + 1, F.length("rest")).alias("tail")))
        cells = long.select("word", "done", "sizes", F.explode(places).alias("c")).select("word", "done", "sizes", "c.*")
        headed = cells.join(dictionary.withColumnRenamed("word", "head"), "head", "left_semi")
        rest = headed.select("word", F.concat("done", "head", F.lit(" ")).alias("done"), F.concat("sizes", F.array("at")).alias("sizes"), F.col("tail").alias("rest"))
        good = rest.join(dictionary.withColumnRenamed("word", "rest"), "rest", "left_semi").select("word", F.concat("done", "rest").alias("split"), "sizes")
        found = good if found is None else found.unionByName(good)
    return found.groupBy("word").agg(F.max_by("split", "sizes").alias("split"))


def rule_cut(attrs: DataFrame, vocab: DataFrame, parts: int = 2) -> DataFrame:
    """Names cut into words: at visible signals, and compound words by the dictionary into up to ``parts``."""
    rows = _words(attrs)
    plain = rows.select("word").distinct().join(vocab.select("word").distinct(), "word", "left_anti").where(F.length("word") >= 4)
    done = rows.join(compound_cuts(plain, vocab, parts), "word", "left").withColumn("long", F.coalesce("split", "word"))
    several = done.groupBy("attr").agg(F.count(F.lit(1)).alias("n"), F.count("split").alias("cut")).where("n > 1 OR cut > 0").select("attr")
    return _regroup(done.join(several, "attr", "left_semi"), "long")


def rule_pattern(attrs: DataFrame, patterns: list[tuple[str, str]] | None = None) -> DataFrame:
    """Names that match a pattern as a whole become its concept."""
    chain = None
    for regex, concept in patterns or PATTERNS:
        hit = F.lower("attr").rlike(regex)
        chain = F.when(hit, concept) if chain is None else chain.when(hit, concept)
    return attrs.select("attr").where("attr IS NOT NULL").distinct().select("attr", chain.alias("words")).where("words IS NOT NULL")


def rule_pattern_table(attrs: DataFrame, rules: DataFrame) -> DataFrame:
    """The same with the rules as a table ``pattern, concept, priority``; of several that match, the one
    of the least priority counts, then the least concept. Every name is tried against every rule, so the
    rules are to be few; Spark broadcasts them if they are."""
    names = attrs.select("attr").where("attr IS NOT NULL").distinct()
    hit = names.join(rules, F.expr("lower(attr) RLIKE pattern"))
    return hit.groupBy("attr").agg(F.min(F.struct("priority", "concept")).alias("m")).select("attr", F.col("m.concept").alias("words"))


def normalize(attrs: DataFrame, vocab: DataFrame, abbreviations: DataFrame, patterns: list[tuple[str, str]] | None = None) -> DataFrame:
    """``attr, words, rule``: abbreviation, then pattern, then cutting, then identity; else ``-``."""
    found = attrs.select("attr").where("attr IS NOT NULL").distinct()
    parts = {"b": rule_abbreviation(attrs, abbreviations), "d": rule_pattern(attrs, patterns), "c": rule_cut(attrs, vocab), "a": rule_identity(attrs, vocab)}
    for letter, rows in parts.items():
        found = found.join(rows.withColumnRenamed("words", f"w_{letter}"), "attr", "left")
    words = F.coalesce(*[F.col(f"w_{x}") for x in parts], F.lower("attr"))
    rule = F.coalesce(*[F.when(F.col(f"w_{x}").isNotNull(), x) for x in parts], F.lit("-"))
    return found.select("attr", words.alias("words"), rule.alias("rule"))


def keyword_tfidf(names: DataFrame) -> DataFrame:
    """``attr, key, score`` from ``names(attr, words)``: the word with the highest tf-idf, ties by word."""
    rows = names.select("attr", F.explode(F.split("words", " ")).alias("word"))
    tf = rows.groupBy("attr", "word").agg(F.count(F.lit(1)).alias("n"))
    size = rows.groupBy("attr").agg(F.count(F.lit(1)).alias("size"))
    df = tf.groupBy("word").agg(F.count(F.lit(1)).alias("df"))
    total = names.agg(F.count_distinct("attr").alias("total"))
    score = F.col("n") / F.col("size") * F.ln(F.col("total") / F.col("df"))
    scored = tf.join(size, "attr").join(df, "word").join(F.broadcast(total)).withColumn("score", score)
    order = Window.partitionBy("attr").orderBy(F.round("score", 9).desc(), "word")
    return scored.withColumn("rank", F.row_number().over(order)).where("rank = 1").select("attr", F.col("word").alias("key"), "score")


def keyword_rank(names: DataFrame, iters: int = 20, damping: float = 0.85) -> DataFrame:
    """``attr, key, score``: the word ranked highest by random walks on the co-occurrence graph."""
    rows = names.select("attr", F.explode(F.array_distinct(F.split("words", " "))).alias("word"))
    met = rows.alias("x").join(rows.alias("y"), F.col("x.attr") == F.col("y.attr")).where("x.word <> y.word")
    links = cut(met.groupBy(F.col("x.word").alias("u"), F.col("y.word").alias("v")).agg(F.count(F.lit(1)).cast("double").alias("w")))
    out = links.groupBy("u").agg(F.sum("w").alias("total"))
    share = cut(links.join(out, "u").select("u", "v", (F.col("w") / F.col("total")).alias("p")))
    every = cut(rows.select("word").distinct())
    rank = every.withColumn("score", F.lit(1.0))
    for i in range(iters):
        flow = share.join(rank, share["u"] == rank["word"]).groupBy(F.col("v").alias("word")).agg(F.sum(F.col("p") * F.col("score")).alias("flow"))
        rank = every.join(flow, "word", "left").select("word", (F.lit(1 - damping) + damping * F.coalesce("flow", F.lit(0.0))).alias("score"))
        if i % 5 == 4:
            rank = cut(rank)
    order = Window.partitionBy("attr").orderBy(F.round("score", 9).desc(), "word")
    return rows.join(rank, "word").withColumn("rank", F.row_number().over(order)).where("rank = 1").select("attr", F.col("word").alias("key"), "score")


def apply_overrides(keys: DataFrame, overrides: DataFrame) -> DataFrame:
    """Manual corrections win: ``overrides(attr, key)``."""
    fixed = overrides.select("attr", F.col("key").alias("fixed"))
    return keys.join(fixed, "attr", "left").withColumn("key", F.coalesce("fixed", "key")).drop("fixed")
