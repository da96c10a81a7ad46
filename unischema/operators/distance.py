"""Anchors, semantic and combined distances, and the alternatives to a given knowledge base."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from unischema.functions.lineage import cut
from unischema.functions.text import cosine
from unischema.operators import inplace
from unischema.operators.knowledge import k_hop
from unischema.operators.literal import literal_pairs_between

#: Words of a document that one task pairs with all others of it.
BLOCK = 256


def anchor(attrs: DataFrame, concepts: DataFrame, eps_t: int = 1, mode: str = "nearest", q: int = 2) -> DataFrame:
    """``attr, concept, d_lit``: concepts within ``eps_t`` of each name.

    Names that are concepts take them at 0 by an equi-join; only the others enter the literal join.
    ``nearest`` keeps all concepts at the least distance, ``any`` all in range.
    """
    names = attrs.select("attr").where("attr IS NOT NULL").distinct()
    known = concepts.select(F.col("concept").alias("attr")).where("attr IS NOT NULL")
    if mode == "any":
        found = literal_pairs_between(names, known, eps_t, q)
        return found.select(F.col("a").alias("attr"), F.col("b").alias("concept"), F.col("d").alias("d_lit"))
    same = names.join(known, "attr", "left_semi").select("attr", F.col("attr").alias("concept"), F.lit(0).alias("d_lit"))
    if eps_t == 0:
        return same
    rest = cut(names.join(known, "attr", "left_anti"))
    if rest.isEmpty():
        return same
    near = literal_pairs_between(rest, known, eps_t, q).select(F.col("a").alias("attr"), F.col("b").alias("concept"), F.col("d").alias("d_lit"))
    order = Window.partitionBy("attr").orderBy("d_lit")
    return same.unionByName(near.withColumn("rank", F.rank().over(order)).where("rank = 1").drop("rank"))


def semantic_distance(pairs: DataFrame, h1: DataFrame, cap: int) -> DataFrame:
    """``a, b, d``: least path length, 0 for equal names, null beyond ``cap``."""
    reach = k_hop(pairs.select(F.col("a").alias("concept")), h1, cap).select(F.col("start").alias("a"), F.col("end").alias("b"), F.col("len").alias("d"))
    own = pairs.select("a", "b").distinct().join(reach, ["a", "b"], "left")
    return own.select("a", "b", F.when(F.col("a") == F.col("b"), 0).otherwise(F.col("d")).alias("d"))


def combined_distance(pairs: DataFrame, concepts: DataFrame, h1: DataFrame, eps_t: int = 1, gamma: int = 3, mode: str = "nearest") -> DataFrame:
    """``a, b, d, case``: path length of the anchors if both names have one, else edit distance.

    In the first case ``d`` is null if all anchors are farther apart than ``gamma``, however close
    the names themselves may be.
    """
    own = pairs.select("a", "b").distinct()
    names = own.select(F.col("a").alias("attr")).union(own.select("b")).distinct()
    anchors = anchor(names, concepts, eps_t, mode)
    left = anchors.select(F.col("attr").alias("a"), F.col("concept").alias("ca"))
    right = anchors.select(F.col("attr").alias("b"), F.col("concept").alias("cb"))
    tied = own.join(left, "a", "left").join(right, "b", "left")
    reach = semantic_distance(tied.where("ca IS NOT NULL AND cb IS NOT NULL").select(F.col("ca").alias("a"), F.col("cb").alias("b")), h1, gamma)
    met = tied.join(reach.select(F.col("a").alias("ca"), F.col("b").alias("cb"), F.col("d").alias("d_sem")), ["ca", "cb"], "left")
    both = F.col("ca").isNotNull() & F.col("cb").isNotNull()
    least = met.groupBy("a", "b").agg(F.bool_or(both).alias("anchored"), F.min("d_sem").alias("d_sem"))
    case = F.when(F.col("anchored"), 1).otherwise(2)
    return least.select("a", "b", F.when(F.col("anchored"), F.col("d_sem")).otherwise(F.levenshtein("a", "b")).cast("int").alias("d"), case.alias("case"))


def related(pairs: DataFrame, concepts: DataFrame, h1: DataFrame, eps_t: int = 1, gamma: int = 3, strict: bool = False, mode: str = "nearest") -> DataFrame:
    """``a, b, related``: the two-case predicate; thresholds inclusive unless ``strict``."""
    limit = F.when(F.col("case") == 1, gamma).otherwise(eps_t)
    within = F.col("d") < limit if strict else F.col("d") <= limit
    return combined_distance(pairs, concepts, h1, eps_t, gamma, mode).select("a", "b", F.coalesce(within, F.lit(False)).alias("related"))


def distance_from_pairs(synonyms: DataFrame) -> DataFrame:
    """A synonym table ``a, b, w`` as a weighted one-hop table, both directions."""
    one = synonyms.select(F.col("a").alias("concept"), F.col("b").alias("neighbour"), F.col("w").cast("double").alias("w"))
    return one.unionByName(synonyms.select(F.col("b").alias("concept"), F.col("a").alias("neighbour"), F.col("w").cast("double").alias("w")))


def cooccurrence_distance(words: DataFrame, everywhere: float = 0.0) -> DataFrame:
    """``a, b, d`` from ``words(doc_id, word)``: a published distance over document frequencies.

    ``d = (max(log fa, log fb) - log fab) / (log N - min(log fa, log fb))``; ``everywhere`` for two
    words that are both in every document, where it is 0 / 0. Pairs are counted in place; of more rows than
    ``inplace.ROWS`` they are exchanged, those of a long document by blocks of its words, in many tasks.
    """
    rows = cut(words.select("doc_id", "word").distinct())
    total = rows.agg(F.count_distinct("doc_id").alias("n"))
    single = rows.groupBy("word").agg(F.count(F.lit(1)).alias("f"))
    if rows.count() <= inplace.ROWS:
        return _counted_in_place(rows, single, total.first()["n"], everywhere)
    blocks = rows.groupBy("doc_id").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("n_blocks"))
    dealt = rows.join(blocks, "doc_id")
    left = dealt.select("doc_id", "word", F.pmod(F.hash("word"), F.col("n_blocks")).alias("block"))
    right = dealt.select("doc_id", "word", F.explode(F.sequence(F.lit(0), F.col("n_blocks") - 1)).alias("block"))
    met = left.alias("x").join(right.alias("y"), (F.col("x.doc_id") == F.col("y.doc_id")) & (F.col("x.block") == F.col("y.block"))).where("x.word < y.word")
    pairs = met.groupBy(F.col("x.word").alias("a"), F.col("y.word").alias("b")).agg(F.count(F.lit(1)).alias("fab"))
    named = pairs.join(single.select(F.col("word").alias("a"), F.col("f").alias("fa")), "a").join(single.select(F.col("word").alias("b"), F.col("f").alias("fb")), "b")
    la, lb = F.ln(F.col("fa").cast("double")), F.ln(F.col("fb").cast("double"))
    d = F.try_divide(F.greatest(la, lb) - F.ln(F.col("fab").cast("double")), F.ln(F.col("n").cast("double")) - F.least(la, lb))
    return named.join(F.broadcast(total)).select("a", "b", F.coalesce(d, F.lit(everywhere)).alias("d"))


def _counted_in_place(rows: DataFrame, single: DataFrame, total: int, everywhere: float) -> DataFrame:
    """``a, b, d`` of distinct ``rows(doc_id, word)``: documents are sorted arrays of their words' numbers."""
    order = F.row_number().over(Window.orderBy("word")).cast("int") - 1
    numbered = cut(single.where("word IS NOT NULL").withColumn("id", order))
    lists = rows.where("doc_id IS NOT NULL").join(numbered.select("word", "id"), "word").groupBy("doc_id").agg(F.sort_array(F.collect_list("id")).alias("ids"))
    names = numbered.orderBy("id").select("word", "f").toArrow()
    texts = lists.select("ids").toArrow()["ids"].combine_chunks()
    ids, bounds = np.asarray(texts.flatten(), dtype="int32"), np.concatenate([[0], np.cumsum(np.asarray(texts.value_lengths(), dtype="int64"))]).astype("int32")
    ends = np.repeat(bounds[1:], np.diff(bounds))
    logs = rows.sparkSession.sparkContext.broadcast(np.log(np.asarray(names["f"], dtype="float64")))

    def measured(first: np.ndarray, second: np.ndarray, n: np.ndarray) -> list[pa.Array]:
        la, lb = logs.value[first], logs.value[second]
        above, below = np.maximum(la, lb) - np.log(n), np.log(total) - np.minimum(la, lb)
        return [pa.array(np.divide(above, below, out=np.full(len(n), everywhere), where=below != 0))]

    # a word meets those after it in each of its documents
    return inplace.pairs_in_place(rows.sparkSession, names["word"].combine_chunks(), ids, np.arange(1, len(ids) + 1, dtype="int32"), ends, ids, "a string, b string, d double", measured)


def edges_from_vectors(vectors: DataFrame, tau: float, lsh_bucket: float | None = None) -> DataFrame:
    """``a, b, cosine`` of vector pairs at ``tau`` or more.

    Exact by a theta join; with ``lsh_bucket`` only pairs that share a bucket of random projections of the
    unit vectors count (may miss some). Those buckets are wide at a low ``tau`` and hold most pairs, so
    pairs are made and kept or dropped in place, by blocks of vectors; only vectors are exchanged.
    """
    if lsh_bucket is None:
        x, y = vectors.alias("x"), vectors.alias("y")
        pairs = x.join(y, F.col("x.vec_id") < F.col("y.vec_id"))
        rows = pairs.select(F.col("x.vec_id").alias("a"), F.col("y.vec_id").alias("b"), cosine(F.col("x.embedding"), F.col("y.embedding")).alias("cosine"))
        return rows.where(F.col("cosine") >= tau)
    from pyspark.ml.feature import BucketedRandomProjectionLSH, Normalizer

    some = vectors.where("vec_id IS NOT NULL AND exists(embedding, v -> v <> 0)")
    if some.isEmpty():
        return some.select(F.col("vec_id").alias("a"), F.col("vec_id").alias("b"), F.lit(0.0).alias("cosine"))
    dense = some.select("vec_id", "embedding", array_to_vector(F.col("embedding").cast("array<double>")).alias("raw"))
    unit = Normalizer(inputCol="raw", outputCol="unit", p=2.0).transform(dense)
    model = BucketedRandomProjectionLSH(inputCol="unit", outputCol="hashes", bucketLength=lsh_bucket, numHashTables=8, seed=5).fit(unit)
    hashes = F.transform("hashes", lambda h: F.get(vector_to_array(h), F.lit(0)))
    return _block_pairs(model.transform(unit).select("vec_id", "embedding", hashes.alias("hashes")), tau)


#: Vectors of one block, and those of it that one step compares with another block.
VECTORS, SLICE = 4096, 256


def _block_pairs(rows: DataFrame, tau: float) -> DataFrame:
    """``a, b, cosine`` of ``rows(vec_id, embedding, hashes)`` at ``tau`` or more with an equal hash at the same place."""
    blocks = -(-rows.count() // VECTORS)
    own = F.pmod(F.xxhash64("vec_id"), F.lit(blocks))
    every = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long")))
    dealt = rows.withColumn("own", own).withColumn("other", every).withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")})
    tasks = max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), blocks)

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group = pa.Table.from_batches(batches)
        wide = lambda name: np.asarray(group[name].combine_chunks().flatten(), dtype="float64").reshape(group.num_rows, -1)
        ids, block, hashes, unit = group["vec_id"].to_numpy(), group["own"].to_numpy(), wide("hashes"), wide("embedding")
        unit /= np.sqrt((unit * unit).sum(axis=1, keepdims=True))
        left, right = (np.flatnonzero(block == group[side][0].as_py()) for side in ("i", "j"))
        for begin in range(0, len(left), SLICE):
            some = left[begin : begin + SLICE]
            found = unit[some] @ unit[right].T
            x, y = np.nonzero(found >= tau)
            p, q, value = some[x], right[y], found[x, y]
            # the pair of blocks has both orders of a pair where the blocks are one
            kept = (hashes[p] == hashes[q]).any(axis=1) & ((ids[p] < ids[q]) if group["i"][0] == group["j"][0] else (ids[p] != ids[q]))
            p, q = ids[p[kept]], ids[q[kept]]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(p, q)), pa.array(np.maximum(p, q)), pa.array(value[kept])], ["a", "b", "cosine"])

    return dealt.drop("other").repartition(tasks, "i", "j").groupBy("i", "j").applyInArrow(meet, "a long, b long, cosine double")
