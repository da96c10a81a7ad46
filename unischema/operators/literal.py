"""The literal join: pairs and clusters of names within an edit distance.

``literal_pairs`` rewrites the similarity predicate into equi-joins: a rare-gram prefix join with a
length filter for words with a positive count bound, and the deletion lane for shorter ones and for
those whose rarest grams are common. Every
candidate is verified with the bounded distance, so the result equals the nested loop's.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from unischema.functions.lineage import cut
from unischema.functions.text import edit_within
from unischema.operators.clusters import merge_all
from unischema.operators.grams import deletion_candidates, deletion_pairs, gram_candidates, gram_frequency, gram_index, prefix_postings


def _verified(pairs: DataFrame, eps: int) -> DataFrame:
    return pairs.select("a", "b", edit_within(F.col("a"), F.col("b"), eps).alias("d")).where("d IS NOT NULL")


#: A gram in more words than this is hot: its words meet on deletion variants, not on the gram.
HOT_GRAM = 128


def _prefix_pairs(x: DataFrame, y: DataFrame, frequency: DataFrame, q: int, eps: int, ordered: bool, hot: int = HOT_GRAM) -> DataFrame:
    """Pairs that share one of their rarest grams.

    A hot gram would pair all its words with each other. A pair that shares no other rare gram has the
    hot one in both prefixes, so the words with a hot gram among their rarest are all joined on their
    deletion variants instead, which nearly only true pairs share.
    """
    left, right = prefix_postings(x, frequency, q, eps), prefix_postings(y, frequency, q, eps)
    on = (F.col("x.gram") == F.col("y.gram")) & (F.col("x.occ") == F.col("y.occ")) & (F.abs(F.col("x.len") - F.col("y.len")) <= eps)
    if ordered:
        on = on & (F.col("x.attr") < F.col("y.attr"))
    cold = F.col("df") <= hot
    pairs = left.where(cold).alias("x").join(right.where(cold).alias("y"), on).select(F.col("x.attr").alias("a"), F.col("y.attr").alias("b"))
    warm = lambda side: side.where(~cold).select("attr").distinct()
    return pairs.unionByName(deletion_pairs(warm(left), warm(right), eps, ordered)).distinct()


def literal_pairs(attrs: DataFrame, eps: int = 1, q: int = 2, bound: str = "max", verify: str = "edit", prefix: bool = True, hot: int = HOT_GRAM) -> DataFrame:
    """``a, b, d`` with a < b of all pairs of distinct attributes within ``eps``.

    ``verify='count'`` returns the count filter's pairs unverified (distance null), with the chosen
    ``bound``; ``prefix=False`` takes the count filter's candidates instead of the prefix join.
    """
    words = attrs.select("attr").where("attr IS NOT NULL").distinct()
    if verify == "count" or not prefix:
        words = cut(words)
    postings = gram_index(words, q)
    if verify == "count":
        return gram_candidates(postings, postings, q, eps, bound).select("a", "b", F.lit(None).cast("int").alias("d"))
    if prefix:
        long = _prefix_pairs(postings, postings, gram_frequency(postings), q, eps, True, hot)
    else:
        long = gram_candidates(postings, postings, q, eps, bound).select("a", "b")
    return _verified(long.unionByName(deletion_candidates(words, words, q, eps)).distinct(), eps)


def literal_pairs_between(left: DataFrame, right: DataFrame, eps: int = 1, q: int = 2) -> DataFrame:
    """``a, b, d`` with a from the left and b from the right, equal names included."""
    l_words, r_words = (df.select("attr").where("attr IS NOT NULL").distinct() for df in (left, right))
    x, y = gram_index(l_words, q), gram_index(r_words, q)
    frequency = gram_frequency(x.unionByName(y))
    pairs = _prefix_pairs(x, y, frequency, q, eps, ordered=False)
    pairs = pairs.unionByName(deletion_candidates(l_words, r_words, q, eps, ordered=False)).distinct()
    return _verified(pairs, eps)


def literal_lookup(names: DataFrame, kept: DataFrame, eps: int = 1, q: int = 2, postings: DataFrame | None = None) -> DataFrame:
    """``a, b, d``: names against kept words, of which ``postings`` may be stored (``grams.write_gram_index``).

    Only the names are cut into grams then; each meets the stored postings of its own grams, and short
    words meet on deletion variants. Nothing is ranked, so that the stored side is read as it is.
    """
    words = names.select("attr").where("attr IS NOT NULL").distinct()
    kept = kept.select("attr").where("attr IS NOT NULL").distinct()
    if eps == 0:
        return words.join(kept, "attr").select(F.col("attr").alias("a"), F.col("attr").alias("b"), F.lit(0).alias("d"))
    stored = gram_index(kept, q) if postings is None else postings.select("attr", "len", "gram", "occ", "pos")
    pairs = gram_candidates(gram_index(words, q), stored, q, eps, ordered=False).select("a", "b")
    return _verified(pairs.unionByName(deletion_candidates(words, kept, q, eps, ordered=False)).distinct(), eps)


def literal_matches(left: dict[str, DataFrame], right: dict[str, DataFrame], eps: int = 1, q: int = 2, lanes: tuple[str, ...] = ("mm", "mh", "hm"), gamma: int | None = None, halo_rule: str = "subtract") -> DataFrame:
    """``left_id, right_id, lane, a, b, d``: matches of two cluster families by the three conditions.

    A family is ``{"member": (cluster_id, attr), "halo": (cluster_id, concept, d_lit, d_sem)}``. The
    halo lanes subtract the concept's literal distance from ``eps``; with ``halo_rule='combined'``
    the name may be within ``eps`` of a halo concept whose semantic distance is at most ``gamma``.
    """
    found = []
    member = lambda side: side["member"].select("cluster_id", "attr")
    halo = lambda side: side["halo"].select("cluster_id", F.col("concept").alias("attr"), "d_lit", "d_sem")
    sides = {"mm": (member, member), "mh": (member, halo), "hm": (halo, member)}
    for lane in lanes:
        take_left, take_right = sides[lane]
        x, y = take_left(left), take_right(right)
        pairs = literal_pairs_between(x, y, eps, q)
        met = pairs.join(x.withColumnRenamed("cluster_id", "left_id").withColumnRenamed("attr", "a"), "a").join(y.withColumnRenamed("cluster_id", "right_id").withColumnRenamed("attr", "b"), "b")
        if lane != "mm":
            if halo_rule == "combined" and gamma is not None:
                met = met.where(F.coalesce("d_sem", F.lit(0)) <= gamma)
            else:
                met = met.where(F.col("d") <= eps - F.coalesce("d_lit", F.lit(0)))
        found.append(met.select("left_id", "right_id", F.lit(lane).alias("lane"), "a", "b", "d"))
    out = found[0]
    for more in found[1:]:
        out = out.unionByName(more)
    return out


def literal_join(left: dict[str, DataFrame], right: dict[str, DataFrame], eps: int = 1, q: int = 2) -> dict[str, DataFrame]:
    """The literal join proper: the three lanes, then the merge of everything that met."""
    pairs = literal_matches(left, right, eps, q).select(F.col("left_id").alias("a"), F.col("right_id").alias("b"))
    both = {k: left[k].unionByName(right[k]).distinct() for k in ("member", "halo")}
    return merge_all(pairs, both)


def self_literal_clusters(attrs: DataFrame, eps: int = 1, q: int = 2, verify: str = "edit", bound: str = "max") -> DataFrame:
    """``cluster_id, attr``: connected names; the id is the least name."""
    from unischema.operators.components import label_nodes

    pairs = literal_pairs(attrs, eps, q, bound, verify)
    return label_nodes(attrs.select(F.col("attr").alias("node")).where("node IS NOT NULL").distinct(), pairs.select("a", "b")).select(F.col("label").alias("cluster_id"), F.col("node").alias("attr"))
