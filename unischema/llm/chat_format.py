"""Chat formatting of reply trees: root-to-leaf paths, ranked branches, one conversation per path.

Messages form trees by ``parent_id``. Paths are enumerated by self-joins that double their reach: each
message knows its ancestor 2^k steps up and its depth, so ``log2(depth)`` joins reach every root, and
a second pass of as many joins hands the chosen leaves' numbers down to all messages on their paths.
Leaves of a tree are ranked by the sum of the scores on their paths, then by depth, then by id; the
best ``branches`` are kept, and each is formatted as one conversation with a loss mask.

The template writes ``<|turn|>role<|text|>text<|end|>`` per message. Inside roles and texts every
control string is broken by a backslash after its first character, and a backslash is doubled, so the
original comes back exactly. Loss spans cover the texts of assistant messages, in code points.

Defined results: null texts and roles count as empty, null scores as 0; a message whose parent is
missing is a root; rows that repeat are messages of their own in linear tables; an empty table gives
an empty result; other columns are ignored; very long texts and very many messages are formatted whole. A cycle of parents has no root and gives no path.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from unischema.llm.common import cut, read_table

TURN, TEXT, END = "<|turn|>", "<|text|>", "<|end|>"
#: Strings broken inside texts: those of this template and of other common ones.
CONTROL = ("<|", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")
LEARNT_ROLE = "assistant"
#: The message that the query adds to the table's conversations.
EXTRA_ID, EXTRA_TEXT = -7, "</s>[INST] ok [/INST]"

_ESCAPED = re.compile(r"\\(.)", re.DOTALL)


def escape(text: Column) -> Column:
    out = F.replace(F.coalesce(text, F.lit("")), F.lit("\\"), F.lit("\\\\"))
    for word in CONTROL:
        out = F.replace(out, F.lit(word), F.lit(f"{word[0]}\\{word[1:]}"))
    return out


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text)


def linear_tree(turns: DataFrame) -> DataFrame:
    """The reply tree of a table of turns: each message answers the one before it.

    ``tree_id, id, parent_id, role, text, score``; ids count from 0 by turn, then role and text.
    """
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    numbered = turns.select("conv_id", "turn", "role", "text", (F.row_number().over(order) - 1).cast("long").alias("id"))
    return numbered.select(F.col("conv_id").alias("tree_id"), "id", F.when(F.col("id") > 0, F.col("id") - 1).alias("parent_id"), "role", "text", F.lit(0.0).alias("score"))


def _ancestors(messages: DataFrame) -> DataFrame:
    """``tree_id, id, depth, total`` of each message that a root reaches: steps up, scores on the way."""
    known = messages.select("tree_id", "id")
    parent = known.select(F.col("tree_id").alias("t"), F.col("id").alias("p"))
    state = messages.join(parent, messages["tree_id"].eqNullSafe(parent["t"]) & (messages["parent_id"] == parent["p"]), "left").select(
        "tree_id", "id", F.col("p").alias("up"), F.when(F.col("p").isNotNull(), 1).otherwise(0).cast("long").alias("depth"), F.coalesce("score", F.lit(0.0)).cast("double").alias("total")
    )
    state = cut(state)
    bound = state.count()
    finished, active = state.where("up IS NULL"), state.where("up IS NOT NULL")
    reach = 1
    while reach <= bound and not active.isEmpty():
        known = finished.unionByName(active)
        above = known.select(F.col("tree_id").alias("t"), F.col("id").alias("p"), F.col("up").alias("up2"), F.col("depth").alias("d2"), F.col("total").alias("s2"))
        met = active.join(above, active["tree_id"].eqNullSafe(above["t"]) & (active["up"] == above["p"]))
        state = cut(met.select("tree_id", "id", F.col("up2").alias("up"), (F.col("depth") + F.col("d2")).alias("depth"), (F.col("total") + F.col("s2")).alias("total")))
        finished, active = finished.unionByName(state.where("up IS NULL")), state.where("up IS NOT NULL")
        reach *= 2
    return finished.drop("up")


def best_leaves(messages: DataFrame, branches: int = 1) -> DataFrame:
    """``tree_id, leaf, depth, rank`` of each tree's best paths."""
    asked = messages.where("parent_id IS NOT NULL").select(F.col("tree_id").alias("t"), F.col("parent_id").alias("p")).distinct()
    reached = _ancestors(messages)
    leaves = reached.join(asked, reached["tree_id"].eqNullSafe(asked["t"]) & (reached["id"] == asked["p"]), "left_anti")
    order = Window.partitionBy("tree_id").orderBy(F.col("total").desc(), F.col("depth").desc(), "id")
    return leaves.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= branches).select("tree_id", F.col("id").alias("leaf"), "depth", "rank")


def path_messages(messages: DataFrame, leaves: DataFrame) -> DataFrame:
    """``tree_id, leaf, rank, place, role, text``: every message on every chosen path.

    Path rows double: a row that knows its ancestor 2^k up adds that ancestor's row, k from the largest.
    """
    jump = messages.select("tree_id", "id", F.col("parent_id").alias("up"))
    deepest = leaves.agg(F.max("depth")).first()[0] or 0
    jumps = []
    step = 1
    while step <= deepest:
        jumps.append(jump)
        above = jump.select(F.col("tree_id").alias("t"), F.col("id").alias("p"), F.col("up").alias("up2"))
        jump = cut(jump.join(above, jump["tree_id"].eqNullSafe(above["t"]) & (jump["up"] == above["p"])).select("tree_id", "id", F.col("up2").alias("up")))
        step *= 2
    rows = leaves.select("tree_id", F.col("leaf").alias("id"), "leaf", "rank", F.col("depth").cast("long").alias("place"))
    for k in range(len(jumps) - 1, -1, -1):
        hop = jumps[k].where("up IS NOT NULL").select(F.col("tree_id").alias("t"), F.col("id").alias("p"), "up")
        more = rows.join(hop, rows["tree_id"].eqNullSafe(hop["t"]) & (rows["id"] == hop["p"])).where(F.col("place") >= (1 << k))
        rows = cut(rows.unionByName(more.select("tree_id", F.col("up").alias("id"), "leaf", "rank", (F.col("place") - (1 << k)).alias("place"))))
    said = messages.select(F.col("tree_id").alias("t"), F.col("id").alias("p"), "role", "text")
    return rows.join(said, rows["tree_id"].eqNullSafe(said["t"]) & (rows["id"] == said["p"])).select("tree_id", "leaf", "rank", "place", "role", "text")


def format_paths(rows: DataFrame) -> DataFrame:
    """``tree_id, leaf, rank, formatted, loss_spans`` (begin and end in code points) per path.

    Places are running sums over a path's messages, so that long paths cost no more for each message.
    """
    role, text = escape(F.col("role")), escape(F.col("text"))
    parts = rows.select("tree_id", "leaf", "rank", "place", F.concat(F.lit(TURN), role, F.lit(TEXT)).alias("head"), text.alias("body"), F.coalesce(F.col("role") == LEARNT_ROLE, F.lit(False)).alias("learn"))
    before = Window.partitionBy("tree_id", "leaf", "rank").orderBy("place", "head", "body").rowsBetween(Window.unboundedPreceding, -1)
    begin = F.coalesce(F.sum(F.length("head") + F.length("body") + len(END)).over(before), F.lit(0)) + F.length("head")
    placed = parts.withColumn("begin", begin.cast("int"))
    message = F.struct("place", "begin", F.concat("head", "body", F.lit(END)).alias("said"), (F.col("begin") + F.length("body")).alias("end"), "learn")
    grouped = placed.groupBy("tree_id", "leaf", "rank").agg(F.sort_array(F.collect_list(message)).alias("ms"))
    spans = F.transform(F.filter("ms", lambda m: m["learn"]), lambda m: F.struct(m["begin"].alias("begin"), m["end"].alias("end")))
    return grouped.select("tree_id", "leaf", "rank", F.array_join(F.transform("ms", lambda m: m["said"]), "").alias("formatted"), spans.alias("loss_spans"))


def format_conversations(messages: DataFrame, branches: int = 1) -> DataFrame:
    """The best ``branches`` paths of each reply tree, formatted.

    ``messages``: ``tree_id, id, parent_id, role, text, score``, ids unique in a tree.
    """
    messages = cut(messages.select("tree_id", "id", "parent_id", "role", "text", "score"))
    return format_paths(path_messages(messages, cut(best_leaves(messages, branches))))


def parse(formatted: str) -> list[tuple[str, str]]:
    """The turns of one formatted conversation, roles and texts as they were."""
    turns = []
    for part in formatted.split(TURN)[1:]:
        role, _, rest = part.partition(TEXT)
        turns.append((unescape(role), unescape(rest.removesuffix(END))))
    return turns


def _hex(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of what the output holds: turns by its markers, learnt text by its loss spans."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for conv, whole, spans in zip(batch["conv_id"], batch["formatted"], batch["loss_spans"], strict=True):
                turns = parse(whole)
                learnt = unescape("".join(whole[s["begin"] : s["end"]] for s in spans))
                said = "".join(f"{role}\n{text}\n" for role, text in turns)
                out.append((conv, len(turns), _hex(said), len(learnt), _hex(learnt), len(whole)))
            yield pd.DataFrame(out, columns=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    rows = formatted.select(F.col("tree_id").alias("conv_id"), "formatted", "loss_spans")
    return rows.mapInPandas(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def op3_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = read_table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    extra = spark.range(2).select(F.lit(EXTRA_ID).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise(LEARNT_ROLE).alias("role"), F.lit(EXTRA_TEXT).alias("text"))
    return read_back(format_conversations(linear_tree(turns.unionByName(extra))))


_SQL_ESCAPED = "replace(coalesce({0}, ''), chr(92), chr(92) || chr(92))"
for _word in CONTROL:
    _SQL_ESCAPED = f"replace({_SQL_ESCAPED}, '{_word}', '{_word[0]}' || chr(92) || '{_word[1:]}')"
ORACLE = f"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT {EXTRA_ID}, 0, 'user', '{EXTRA_TEXT}' UNION ALL SELECT {EXTRA_ID}, 1, '{LEARNT_ROLE}', '{EXTRA_TEXT}'
)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
       coalesce(sum(length(text)) FILTER (WHERE role = '{LEARNT_ROLE}'), 0)::BIGINT AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = '{LEARNT_ROLE}'), '')) AS loss_sha256,
       sum({len(TURN) + len(TEXT) + len(END)} + length({_SQL_ESCAPED.format('role')}) + length({_SQL_ESCAPED.format('text')}))::BIGINT AS formatted_chars
FROM c GROUP BY conv_id
"""
