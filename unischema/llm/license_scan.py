"""License scanning by ordered signature rules with a keyword prefilter, all in SQL expressions.

A text is folded once to its words joined by single blanks. A few *gates* (short strings, one of which
is in every keyword) decide whether any rule of a gate is looked at; then a rule is tried only if the
text contains its keyword. Every match is a detection: an interval of words with the rule's label,
priority and confidence. Detections are swept by begin, longest first: one that lies inside an earlier
interval of at least its priority is suppressed; of equal intervals the higher priority stays, then the
earlier rule. Matches of the base rules are always reported.

Patterns are literals of the plan, so that each is compiled once for a task. All steps are linear in a
text's words and nearly so in its detections, so texts may be very long.

Defined results: a null text is empty; a text without detections has empty label strings, null
first and last words and score 0; nested and repeated matches are as above; rows that repeat are each
returned; an empty table gives an empty result; columns beyond ``doc_id`` and ``text`` are ignored.
Texts are scanned whole.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unischema.llm.common import GAP, fold_ascii, let, read_table
from unischema.llm.license_rules import Rule, all_rules, gate_of

PRIORITIES = 3
#: Detections that are folded one by one; the blocks are joined by their furthest ends.
BLOCK = 256
_DETECTION = "struct<begin:int,minus_end:int,minus_priority:int,number:int,label:string,confidence:double,base:boolean>"
_NONE = f"array<{_DETECTION}>"


def _spaces(text: Column) -> Column:
    return F.length(text) - F.length(F.replace(text, F.lit(" "), F.lit("")))


def _rule_table(rules: list[Rule]) -> Column:
    """What is known of each rule, by number: one constant of the plan."""
    cells = [{"label": r.label, "priority": r.priority, "confidence": r.confidence, "base": r.base} for r in rules]
    return F.from_json(F.lit(json.dumps(cells)), "array<struct<label:string,priority:int,confidence:double,base:boolean>>")


def _hits(joined: Column, rules: list[Rule]) -> Column:
    """``number, marked``: for each rule whose gate and keyword are there, the text with its matches in angle brackets.

    Kept to a few expressions a rule, as all of them are in the plan.
    """
    by_gate: dict[str, list[Column]] = {}
    for number, rule in enumerate(rules):
        marked = F.regexp_replace(joined, F.lit(f"(?<= )(?:{rule.pattern})(?= )"), F.lit("<$0>"))
        by_gate.setdefault(gate_of(rule), []).append(F.when(F.contains(joined, F.lit(rule.keyword)), F.struct(F.lit(number).alias("number"), marked.alias("marked"))))
    gated = [F.when(F.contains(joined, F.lit(gate)), F.array(*found)) for gate, found in by_gate.items()]
    present = lambda cells: F.filter(cells, lambda x: x.isNotNull())
    return present(F.flatten(present(F.array(*gated))))


def _detections(joined: Column, rules: list[Rule]) -> Column:
    """All matches of all rules in `` w0 w1 ... ``, unordered.

    Words hold no angle brackets, as those separate words, and matches of one rule do not overlap, so the
    marked words' places are the matches' begins and ends, in order.
    """
    table = _rule_table(rules)

    def places(hit: Column) -> Column:
        def ends_of(words: Column) -> Column:
            every = F.sequence(F.lit(0), F.size(words) - 1)
            begins = F.filter(every, lambda i: F.startswith(F.get(words, i), F.lit("<")))
            ends = F.filter(every, lambda i: F.endswith(F.get(words, i), F.lit(">")))
            return F.arrays_zip(begins.alias("begin"), ends.alias("last"))

        def detection(rule: Column) -> Column:
            return F.transform(
                let(F.split(F.trim(hit["marked"]), " "), ends_of),
                lambda m: F.struct(
                    m["begin"].alias("begin"), (-m["last"] - 1).alias("minus_end"), (-rule["priority"]).alias("minus_priority"), hit["number"].alias("number"),
                    rule["label"].alias("label"), rule["confidence"].alias("confidence"), rule["base"].alias("base"),
                ).cast(_DETECTION),
            )

        return let(F.get(table, hit["number"]), detection)

    return F.flatten(F.transform(_hits(joined, rules), places))


def _end(d: Column) -> Column:
    return -d["minus_end"]


def _surviving(found: Column) -> Column:
    """Sweeps sorted detections. ``reach`` is the furthest end so far of each priority or a higher one.

    Blocks are swept one by one from the reach of all before them, which is that of their furthest ends
    (a suppressed detection reaches no further than the one that hides it).
    """
    none = F.array_repeat(F.lit(-1), PRIORITIES)

    def further(reach: Column, d: Column) -> Column:
        return F.transform(reach, lambda far, level: F.when(level + 1 <= -d["minus_priority"], F.greatest(far, _end(d))).otherwise(far))

    def swept(block: Column, reach: Column) -> Column:
        start = F.struct(reach.alias("reach"), F.array().cast(_NONE).alias("kept"))

        def step(acc: Column, d: Column) -> Column:
            hidden = F.get(acc["reach"], -d["minus_priority"] - 1) >= _end(d)
            return F.when(hidden, acc).otherwise(F.struct(further(acc["reach"], d).alias("reach"), F.concat(acc["kept"], F.array(d)).alias("kept")))

        return F.aggregate(block, start, step)["kept"]

    def by_block(blocks: Column) -> Column:
        tops = F.transform(blocks, lambda block: F.aggregate(block, none, further))
        wider = lambda x, y: F.zip_with(x, y, lambda u, v: F.greatest(u, v))
        start = F.struct(none.alias("reach"), F.array().cast("array<array<int>>").alias("before"))
        before = F.aggregate(tops, start, lambda acc, top: F.struct(wider(acc["reach"], top).alias("reach"), F.concat(acc["before"], F.array(acc["reach"])).alias("before")))["before"]
        return let(before, lambda reaches: F.flatten(F.transform(blocks, lambda block, k: swept(block, F.get(reaches, k)))))

    blocks = F.transform(F.sequence(F.lit(0), F.floor((F.size(found) - 1) / BLOCK).cast("int")), lambda k: F.slice(found, k * BLOCK + 1, BLOCK))
    return F.when(F.size(found) <= BLOCK, swept(found, none)).otherwise(let(blocks, by_block))


def scan_licenses(docs: DataFrame, rules: list[Rule] | None = None) -> DataFrame:
    """``doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, detections``."""
    rules = rules or all_rules()
    folded = F.trim(F.regexp_replace(fold_ascii(F.col("text")), GAP, " "))

    def scan(body: Column) -> Column:
        joined = F.concat(F.lit(" "), body, F.lit(" "))
        found = let(joined, lambda j: F.sort_array(_detections(j, rules)))
        n_words = F.when(body == "", 0).otherwise(_spaces(body) + 1).cast("long")
        return F.struct(n_words.alias("n_words"), found.alias("found"))

    rows = docs.select("doc_id", let(folded, scan).alias("x")).select("doc_id", "x.n_words", "x.found")
    rows = rows.withColumns({"kept": _surviving(F.col("found")), "bases": F.filter("found", lambda d: d["base"])})
    starts = F.transform("bases", lambda d: d["begin"].cast("long"))
    names = lambda cells: F.transform(cells, lambda d: d["label"])
    joined = lambda labels: F.array_join(F.array_sort(F.array_distinct(labels)), ",")
    span = lambda d: F.struct(d["begin"].alias("begin"), (-d["minus_end"]).alias("end"), d["label"].alias("label"), (-d["minus_priority"]).alias("priority"), d["confidence"].alias("confidence"))
    return rows.select(
        "doc_id",
        "n_words",
        F.size("bases").cast("long").alias("n_base"),
        F.array_min(starts).alias("first_word"),
        F.array_max(starts).alias("last_word"),
        joined(names("bases")).alias("base_labels"),
        joined(F.concat(names("bases"), names("kept"))).alias("labels"),
        F.coalesce(F.array_max(F.transform(F.concat("kept", "bases"), lambda d: d["confidence"])), F.lit(0.0)).alias("score"),
        F.transform("kept", span).alias("detections"),
    )


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(read_table(spark, sf_dir, "documents")).drop("detections")
