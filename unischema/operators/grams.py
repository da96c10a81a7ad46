"""q-gram postings, count-filter candidates, prefix filter and the short lane.

Shared grams are counted as a bag by numbering the occurrences of each gram in a word, so that bag
intersection is an equi-join on (gram, occurrence). The count filter is necessary, not sufficient;
callers verify the distance. Words too short for a positive bound share no gram with certainty and
are joined on their deletion variants instead.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from unischema.functions.lineage import cut
from unischema.functions.text import count_bound, count_bound_self, deletions, numbered_grams


def gram_index(attrs: DataFrame, q: int) -> DataFrame:
    """``attr, len, gram, occ, pos``: the postings of distinct non-null attributes."""
    words = attrs.select("attr").where("attr IS NOT NULL").distinct()
    return words.select("attr", F.length("attr").alias("len"), F.explode(numbered_grams(F.col("attr"), q)).alias("g")).select("attr", "len", "g.*")


def gram_frequency(postings: DataFrame) -> DataFrame:
    return postings.groupBy("gram", "occ").agg(F.count(F.lit(1)).alias("df"))


def write_gram_index(attrs: DataFrame, q: int, path: str) -> None:
    """The index as files sorted by gram, one folder per q, for reuse by later joins."""
    gram_index(attrs, q).withColumn("q", F.lit(q)).repartition("gram", "occ").sortWithinPartitions("gram", "occ").write.mode("overwrite").partitionBy("q").parquet(path)


def read_gram_index(spark, path: str, q: int) -> DataFrame:
    return spark.read.parquet(path).where(F.col("q") == q).drop("q")


def _bound(la: Column, lb: Column, q: int, eps: int, bound: str) -> Column:
    return count_bound(la, lb, q, eps) if bound == "max" else count_bound_self(la, q, eps)


def gram_candidates(x: DataFrame, y: DataFrame, q: int, eps: int, bound: str = "max", ordered: bool = True, position: bool = False) -> DataFrame:
    """``a, b, shared`` of pairs that pass the count filter, from two posting tables.

    ``ordered`` keeps a < b for self joins. ``position`` adds the (unsound on numbered grams, hence
    optional) filter on gram places. With ``bound='self'`` a self join links a pair if either word's own
    bound is met, as each word is looked up in turn. A table of postings with itself goes by
    ``_self_candidates``, which lists no pair that only shares common grams.
    """
    if x is y and ordered and not position:
        return _self_candidates(x, q, eps, bound)
    met = x.alias("x").join(y.alias("y"), (F.col("x.gram") == F.col("y.gram")) & (F.col("x.occ") == F.col("y.occ")))
    if ordered:
        met = met.where(F.col("x.attr") < F.col("y.attr"))
    if position:
        met = met.where(F.abs(F.col("x.pos") - F.col("y.pos")) <= eps)
    counted = met.groupBy(F.col("x.attr").alias("a"), F.col("y.attr").alias("b"), F.col("x.len").alias("la"), F.col("y.len").alias("lb")).agg(F.count(F.lit(1)).alias("shared"))
    current = F.least("la", "lb") if ordered else F.col("la")
    least = _bound(F.col("la"), F.col("lb"), q, eps, bound) if bound == "max" else _bound(current, current, q, eps, bound)
    return counted.where(F.col("shared") >= F.greatest(least, F.lit(1)))


#: Words with one gram among their rarest that one task pairs with all others of the gram.
GRAM_BLOCK = 16_384


def _self_candidates(postings: DataFrame, q: int, eps: int, bound: str) -> DataFrame:
    """``gram_candidates`` of a table with itself, a < b.

    With the grams of all words in one order, rarest first, words of ``n`` grams that share ``t`` share
    one of the first ``n - t + 1`` of each, so only those are joined. Each pair is made at its first
    common gram, so none is exchanged or made distinct. Gram sets as 128 bits drop most others:
    each bit that one word alone has is a gram that it does not share. The count itself is exact.
    """
    # grams are numbered in their order
    order = cut(gram_frequency(postings).orderBy("df", "gram", "occ").select("gram", "occ", F.monotonically_increasing_id().alias("g")))
    place = F.pmod(F.xxhash64("g"), F.lit(128)).cast("int")
    bits = lambda low: F.bit_or(F.when((place < 64) if low else (place >= 64), F.call_function("shiftleft", F.lit(1).cast("long"), place % 64)).otherwise(0))
    words = postings.join(order, ["gram", "occ"]).groupBy("attr", "len").agg(F.sort_array(F.collect_list("g")).alias("gs"), bits(True).alias("low"), bits(False).alias("high"))
    rows = cut(words).withColumn("n", F.size("gs")).select("attr", "len", "n", "low", "high", "gs", F.posexplode("gs").alias("r", "g"))
    # the longer word of the two, ``y``, sets the bound with "max", the shorter one with "self"
    own = lambda n: F.greatest(n - q * eps, F.lit(1))
    least = own(F.col("y.n") if bound == "max" else F.col("x.n"))
    # rows of a gram meet by the size that sets the bound: that of ``y``, or of ``x`` in classes of two sizes
    # (exploded also where it is one, as the optimizer infers filters from equal columns without end)
    if bound == "max":
        x = rows.withColumn("m", F.explode(F.sequence(F.col("n"), F.col("n") + q * eps))).where(F.col("r") <= F.col("n") - own(F.col("m")))
        y = rows.withColumn("m", F.explode(F.array("n"))).where(F.col("r") <= F.col("n") - own(F.col("n")))
    else:
        size_class = F.floor((F.greatest(F.col("n"), F.lit(q * eps + 1)) - q * eps) / 2).cast("int")
        x = rows.withColumn("m", F.explode(F.array(size_class))).where(F.col("r") <= F.col("n") - own(F.col("n")))
        y = rows.withColumn("m", F.explode(F.sequence(F.lit(0), size_class))).where(F.col("r") <= F.col("n") - own(F.col("m") * 2 + q * eps))
    hot = x.groupBy("g", "m").agg(F.ceil(F.count(F.lit(1)) / GRAM_BLOCK).cast("int").alias("blocks")).where("blocks > 1")
    x, y = (side.join(hot, ["g", "m"], "left").withColumn("blocks", F.coalesce("blocks", F.lit(1))) for side in (x, y))
    x = x.withColumn("block", F.pmod(F.hash("attr"), F.col("blocks")))
    y = y.withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    alone = lambda one, other: sum(F.bit_count(F.col(f"{one}.{half}").bitwiseAND(F.bitwise_not(F.col(f"{other}.{half}")))) for half in ("low", "high"))
    on = (F.col("x.g") == F.col("y.g")) & (F.col("x.m") == F.col("y.m")) & (F.col("x.block") == F.col("y.block")) & (F.col("x.n") <= F.col("y.n"))
    for side, other in (("x", "y"), ("y", "x")):
        on = on & (F.col(f"{side}.r") <= F.col(f"{side}.n") - least) & (alone(side, other) <= F.col(f"{side}.n") - least)
    on = on & ((F.col("x.n") < F.col("y.n")) | (F.col("x.attr") < F.col("y.attr")))
    shared = F.array(F.array_intersect("x.gs", "y.gs"))
    right = F.filter(shared, lambda s: (F.get(s, F.lit(0)) == F.col("x.g")) & (F.size(s) >= least))
    met = x.alias("x").join(y.alias("y"), on).withColumn("shared", F.explode(F.transform(right, lambda s: F.size(s).cast("long"))))
    a, b = F.least("x.attr", "y.attr"), F.greatest("x.attr", "y.attr")
    size = lambda name: F.when(name == F.col("x.attr"), F.col("x.len")).otherwise(F.col("y.len"))
    return met.select(a.alias("a"), b.alias("b"), size(a).alias("la"), size(b).alias("lb"), "shared")


def prefix_postings(postings: DataFrame, frequency: DataFrame, q: int, eps: int) -> DataFrame:
    """The ``q * eps + 1`` rarest postings of each attribute, with their ``df``: one of them is shared by every match."""
    ranked = postings.join(frequency, ["gram", "occ"], "left").withColumn("df", F.coalesce("df", F.lit(0)))
    order = Window.partitionBy("attr").orderBy("df", "gram", "occ")
    return ranked.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= q * eps + 1).drop("rank")


def short_limit(q: int, eps: int) -> int:
    """Words up to this length have no positive bound."""
    return q - 1 + q * eps


def deletion_pairs(x: DataFrame, y: DataFrame, eps: int, ordered: bool = True) -> DataFrame:
    """``a, b`` of words that share a variant of up to ``eps`` deletions; all within ``eps`` do."""
    variants = lambda df: df.select("attr", F.explode(deletions(F.col("attr"), eps)).alias("variant"))
    met = variants(x).alias("x").join(variants(y).alias("y"), "variant")
    if ordered:
        met = met.where(F.col("x.attr") < F.col("y.attr"))
    return met.select(F.col("x.attr").alias("a"), F.col("y.attr").alias("b")).distinct()


def deletion_candidates(x: DataFrame, y: DataFrame, q: int, eps: int, ordered: bool = True) -> DataFrame:
    """The same for words too short for a positive count bound."""
    short = lambda df: df.select("attr").where(F.length("attr") <= short_limit(q, eps)).distinct()
    return deletion_pairs(short(x), short(y), eps, ordered)
