"""Brute force for operators that SQL cannot express, odd input for all of them, very long texts, recall."""

import itertools
import math
import os
import random
import re
import time
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from unischema.llm import chat_format, decontamination, exact_dedup, language_id, license_rules, license_scan, line_dedup, near_dedup, packing, quality, sharding
from unischema.llm.license_rules import Rule

from .test_llm import ODD, brute_components, docs, fold, words_of

SF = "/root/testdata/sf0.01"


def table(spark, name, sf=SF):
    return spark.read.parquet(f"{sf}/{name}.parquet")


# ---------------------------------------------------------------- quality classifier


def test_factorisation_machine_equals_the_explicit_pair_sum(spark):
    rng = np.random.default_rng(4)
    machine = quality.FactorisationMachine()
    machine.linear[:] = rng.normal(size=machine.linear.shape)
    machine.factors[:] = rng.normal(size=machine.factors.shape)
    machine.bias = 0.3
    make = quality.Featuriser()
    for text in ("A short text, with some words.", "x", "", "one two two THREE 3 !!"):
        index, x = machine._join(make(text, 5))
        pairs = sum(x[i] * x[j] * float(machine.factors[index[i]] @ machine.factors[index[j]]) for i in range(len(x)) for j in range(i + 1, len(x)))
        explicit = machine.bias + float(machine.linear[index] @ x) + pairs
        assert math.isclose(machine.raw(make(text, 5)), explicit, rel_tol=1e-9, abs_tol=1e-9)


def test_quality_on_held_out_rows(spark):
    labels = {r["doc_id"]: r["quality"] for r in table(spark, "labels").collect()}
    held = [r for r in quality.op4_quality_classifier(spark, SF).collect() if r["held_out"] and labels.get(r["doc_id"]) is not None]
    assert len(held) > 80 and sum(r["predicted"] == labels[r["doc_id"]] for r in held) / len(held) > 0.95
    ones, zeros = [[r["score"] for r in held if labels[r["doc_id"]] == k] for k in (1, 0)]
    better = sum((a > b) + 0.5 * (a == b) for a in ones for b in zeros) / (len(ones) * len(zeros))
    assert better > 0.98


def test_quality_odd_input(spark):
    rows = docs(spark, [*ODD, (3, "again"), (None, "q")])
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(12)] + [(0, 1, 0), (None, 1, None)], "doc_id long, quality int, toxic int")
    machine = quality.fit(rows, labels)
    got = quality.score_quality(rows, machine).collect()
    assert len(got) == rows.count() and all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5) for r in got)
    assert quality.score_quality(rows.limit(0), quality.fit(rows.limit(0), labels)).count() == 0
    assert quality.score_quality(rows.select("doc_id", "text"), machine).count() == rows.count()
    assert quality.training_rows(rows, labels, 3).count() <= 3


# ---------------------------------------------------------------- license scan


def brute_licenses(text, rules):
    """Python's regexes with the same gates, marks and suppression, detection by detection."""
    words = words_of(text)
    joined = f" {' '.join(words)} " if words else "  "
    found = []
    for number, rule in enumerate(rules):
        if rule.keyword not in joined:
            continue
        for m in re.finditer(f"(?<= )(?:{rule.pattern})(?= )", joined):
            begin = joined[: m.start()].count(" ") - 1
            found.append((begin, -(begin + m[0].count(" ") + 1), -rule.priority, number))
    found.sort()
    kept = []
    for d in found:
        if not any(k[1] <= d[1] and k[2] <= d[2] for k in kept):
            kept.append(d)
    bases = [d for d in found if rules[d[3]].base]
    label = lambda ds: ",".join(sorted({rules[d[3]].label for d in ds}))
    starts = [d[0] for d in bases]
    score = max([rules[d[3]].confidence for d in kept + bases], default=0.0)
    return len(words), len(bases), min(starts, default=None), max(starts, default=None), label(bases), label(kept + bases), score


def example(rule: Rule) -> str:
    """A text that a rule's pattern matches: the first branch of each group, once."""
    text = rule.pattern
    while re.search(r"\((?:\?:)?[^()]*\)", text):
        text = re.sub(r"\((?:\?:)?([^()|]*)(?:\|[^()]*)?\)(?:[?*]|\{[^}]*\})?", r"\1", text, count=1)
    text = re.sub(r"\[(\w)[^\]]*\]", r"\1", text)
    text = re.sub(r"\\d", "2", re.sub(r"\\[wS][+*]?", "name", text))
    return re.sub(r"(.)\?", r"\1", text)


def test_every_license_rule_passes_its_own_gate(spark):
    rules = license_rules.all_rules()
    assert len(rules) - len(license_rules._IDENTIFIERS) >= 250 and [r.label for r in rules[:4]] == ["gpl", "apache", "cc-by", "mit"]
    texts = [example(r) for r in rules]
    for rule, text in zip(rules, texts, strict=True):
        assert re.fullmatch(rule.pattern, text), (rule, text)
        assert rule.keyword in text and license_rules.gate_of(rule) in text, rule
    got = {r["doc_id"]: r["labels"].split(",") for r in license_scan.scan_licenses(docs(spark, texts)).collect()}
    for i, text in enumerate(texts):
        assert ",".join(got[i]) == brute_licenses(text, rules)[5], text


def test_license_scan_equals_python_regexes(spark):
    rules, rng = license_rules.all_rules(), random.Random(12)
    filler = ["see", "the", "file", "license", "of", "MIT", "cc", "by", "Version", "2.0", "gnu", "public", "or", "later"]
    texts = list(ODD)
    for _ in range(150):
        parts = [example(rng.choice(rules)) if rng.random() < 0.4 else rng.choice(filler) for _ in range(rng.randrange(1, 30))]
        texts.append(rng.choice([" ", ", ", "\n"]).join(parts).title() if rng.random() < 0.3 else " ".join(parts))
    texts += ["mit license " * 700, "gnu general public license version 2 0 " * 300]
    got = {r["doc_id"]: tuple(r)[1:8] for r in license_scan.scan_licenses(docs(spark, texts)).collect()}
    for i, text in enumerate(texts):
        assert got[i] == brute_licenses(text, rules), text and text[:200]
    assert license_scan.scan_licenses(docs(spark, texts).limit(0)).count() == 0
    assert license_scan.scan_licenses(docs(spark, [(1, "mit license"), (1, "mit license"), (None, "x")])).count() == 3


BASES = {"gpl": "gnu general public license", "apache": "apache license", "cc-by": "cc by", "mit": "mit license"}


def test_license_base_columns_on_the_documents(spark):
    got = {r["doc_id"]: r for r in license_scan.op6_license_scan(spark, SF).collect()}
    for r in table(spark, "documents").collect():
        words = words_of(r["text"])
        places = sorted((i, label) for label, phrase in BASES.items() for i in range(len(words)) if words[i : i + len(phrase.split())] == phrase.split())
        own = got[r["doc_id"]]
        assert own["n_words"] == len(words) and own["n_base"] == len(places) and own["base_labels"] == ",".join(sorted({x for _, x in places}))
        assert (own["first_word"], own["last_word"]) == ((places[0][0], places[-1][0]) if places else (None, None))
        assert set(filter(None, own["base_labels"].split(","))) <= set(own["labels"].split(","))


# ---------------------------------------------------------------- language, shards, packing


def test_language_equals_brute_force_and_holds_out(spark):
    rows = table(spark, "documents")
    model = language_id.fit(rows)
    got = {r["doc_id"]: r for r in language_id.identify(rows, model).collect()}
    truth = {r["doc_id"]: (r["text"], r["lang"]) for r in rows.collect()}

    def word_scores(word):
        if word in model.words:
            return model.words[word]
        for n in range(language_id.LONGEST_GRAM, 0, -1):
            framed = word if n == 1 else f"_{word}_"
            known = [model.by_size[n - 1][framed[i : i + n]] for i in range(max(0, len(framed) - n + 1)) if framed[i : i + n] in model.by_size[n - 1]]
            if known:
                return np.mean(known, axis=0)
        return np.zeros(len(model.langs))

    for doc, (text, _) in sorted(truth.items())[:300]:
        words = re.findall(r"[^\W\d_]+", (text or "").lower())
        if not any(c.isalpha() for w in words for c in w):
            assert got[doc]["lang_pred"] == "und" and got[doc]["score"] == 0
            continue
        total = sum((word_scores(w) for w in words), np.zeros(len(model.langs)))
        best = max(total)
        assert math.isclose(total[model.langs.index(got[doc]["lang_pred"])], best, rel_tol=1e-9)
    held = [(got[d]["lang_pred"], lang) for d, (_, lang) in truth.items() if got[d]["held_out"] and lang is not None and got[d]["lang_pred"] != "und"]
    assert len(held) > 200 and sum(a == b for a, b in held) / len(held) > 0.98


def test_language_odd_input(spark):
    rows = docs(spark, [*ODD, (3, "again"), (None, "q"), "wort " * 200_000])
    model = language_id.fit(rows)
    assert language_id.identify(rows, model).count() == rows.count() and language_id.identify(rows.limit(0), model).count() == 0
    clash = rows.withColumns({"held_out": F.lit(1), "lang_pred": F.lit("x"), "score": F.lit(2)})
    assert language_id.identify(clash, model).columns == ["doc_id", "held_out", "lang_pred", "score"]


def _murmur_free_score(spark, key, shard):
    """The hash of the rule, asked of Spark alone; the rest of the score in Python."""
    h = spark.range(1).select(F.xxhash64(F.lit(key).cast("long"), F.lit(shard))).first()[0]
    u = (((h & ((1 << 64) - 1)) >> 11) + 0.5) / float(1 << 53)
    return -1.0 / math.log(u)


def test_shards_are_the_largest_recomputed_scores(spark):
    rows = {r["doc_id"]: r["shard"] for r in sharding.op8_rendezvous_sharding(spark, "/root/testdata/sf0.001").collect()}
    for key in sorted(rows)[:12]:
        scores = [_murmur_free_score(spark, key, s) for s in range(40)]
        assert rows[key] == scores.index(max(scores))


def test_shards_cover_the_documents(spark):
    rows = sharding.op8_rendezvous_sharding(spark, SF).collect()
    texts = {r["doc_id"]: (r["text"] or "").encode() for r in table(spark, "documents").collect()}
    by_shard = defaultdict(list)
    for r in rows:
        assert r["size"] == len(texts[r["doc_id"]]) + 16 and r["text_crc32"] == zlib.crc32(texts[r["doc_id"]]) and r["grown_shard"] in (r["shard"], 40)
        by_shard[r["shard"]].append(r["slot"])
    assert len(rows) == len(texts) and set(by_shard) <= set(range(40)) and all(sorted(s) == list(range(len(s))) for s in by_shard.values())
    assert sharding.rendezvous_shards(docs(spark, ODD).limit(0), [1.0] * 4).count() == 0


def fewest_bins(lengths, capacity):
    """Exact, by trying every placement with the largest first."""
    lengths = sorted(lengths, reverse=True)
    best = [len(lengths)]

    def place(i, rooms):
        if len(rooms) >= best[0]:
            return
        if i == len(lengths):
            best[0] = len(rooms)
            return
        for k in {r: k for k, r in enumerate(rooms) if r >= lengths[i]}.values():
            place(i + 1, rooms[:k] + [rooms[k] - lengths[i]] + rooms[k + 1 :])
        place(i + 1, [*rooms, capacity - lengths[i]])

    place(0, [])
    return best[0]


def test_bins_lie_between_the_bound_and_best_fit(spark):
    rng = random.Random(3)
    for _ in range(60):
        lengths = np.array([rng.randrange(1, 101) for _ in range(rng.randrange(1, 10))])
        exact = fewest_bins(lengths.tolist(), 100)
        bins, _, rooms = packing.best_fit(lengths, 100)
        assert packing.lower_bound(lengths, 100) <= exact <= len(rooms) <= math.ceil(11 * exact / 9 + 6 / 9)
        for at in set(bins.tolist()):
            assert lengths[bins == at].sum() <= 100


def test_packing_of_the_documents_is_certified(spark):
    packed = packing.op10_best_fit_packing(spark, SF)
    rows = packed.collect()
    lengths = np.array([r["length"] for r in rows], np.int64)
    bound, used = packing.lower_bound(lengths), len({r["sequence_id"] for r in rows})
    assert bound <= used <= bound * 1.01 + 1
    ends = defaultdict(int)
    for r in sorted(rows, key=lambda r: (r["sequence_id"], r["offset"])):
        assert r["offset"] == ends[r["sequence_id"]]
        ends[r["sequence_id"]] += r["length"]
    assert max(ends.values()) <= packing.CAPACITY
    assert packing.best_fit_packing(docs(spark, [(1, "same"), (1, "same"), (None, "x")])).count() == 3


def test_repacking_rounds_reach_one_group(spark):
    rng = random.Random(5)
    rows = spark.createDataFrame([(i, 0, 0, rng.choice([700, 900, 1100, 1300]), i) for i in range(2000)], packing.PIECES)
    pieces = packing.cut(rows)
    report = packing.pack_report(packing.pack_pieces(pieces, group_pieces=32))
    assert report["bound"] <= report["sequences"] <= report["bound"] * 1.12


# ---------------------------------------------------------------- near duplicates


def test_near_dedup_beyond_the_limits_of_one_task(spark):
    """The same components by star steps and shuffled labels as by one task and broadcast ones."""
    rng = random.Random(7)
    rows = []
    for base in range(6):
        w = [f"{base}v{i}" for i in range(60)]
        for _ in range(12):
            v = list(w)
            for _ in range(rng.randrange(0, 4)):
                v[rng.randrange(len(v))] = f"e{rng.randrange(10**6)}"
            rows.append(" ".join(v))
    got = sorted(map(tuple, near_dedup.near_duplicates(docs(spark, rows), local_links=0, label_rows=0).collect()))
    assert got == brute_components(list(enumerate(rows)))


def test_near_dedup_recall_against_sql(spark):
    """Components of all documents at sf0.1 as the exact SQL form has them."""
    sf = "/root/testdata/sf0.1"
    if not os.path.isdir(sf):
        pytest.skip("no large table here")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{sf}/documents.parquet')")
    want = {r[0]: (r[1], r[2]) for r in con.sql(f"SELECT doc_id, n_shingles, component_id FROM ({near_dedup.ORACLE})").fetchall()}
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dedup.op5_minhash_near_dedup(spark, sf).collect()}
    assert len(got) == len(want) and sum(got[i] == want[i] for i in want) / len(want) >= 0.999


def test_parity_and_sketch_drop_no_link():
    """Pairs just above the similarity pass all tests that come before the sets."""
    rng = np.random.default_rng(6)
    columns = len(near_dedup._CARRIED)
    cells = len(near_dedup._SHORT_COLUMNS)
    for n in (7, 40, 160, 700, 3000):
        for _ in range(20):
            change = n // 7  # similarity of (n - c) / (n + c) at 0.75 or more
            base = rng.integers(0, 1 << 63, n + change, dtype=np.uint64)
            x, y = np.unique(base[:n]), np.unique(base[change:])
            (sx, mx), (sy, my) = near_dedup.signature(x), near_dedup.signature(y)
            assert len(mx) == columns and 100 * len(np.intersect1d(x, y)) >= 75 * len(np.union1d(x, y))
            flips = sum(bin(int(a) & (2**64 - 1) ^ int(b) & (2**64 - 1)).count("1") for a, b in zip(mx[-16:], my[-16:], strict=True))
            lacking = (len(x) + len(y)) / 7
            assert flips <= min(lacking, (1 - math.exp(-2 * lacking / 1024)) * 512 + near_dedup.PARITY_SLACK)
            sketch = sum(sum(((int(a) ^ int(b)) >> (4 * k)) & 15 != 0 for k in range(16)) for a, b in zip(mx[cells : cells + 12], my[cells : cells + 12], strict=True))
            assert sketch <= near_dedup.SKETCH_DISTANCE and (sx != sy).sum() <= near_dedup.DISTANCE


def test_odd_rows_of_near_dedup(spark):
    rows = docs(spark, [*ODD, (3, "a"), (None, "one two three four five six"), (70, "one two three four five six"), (70, "one two three four five six")])
    got = near_dedup.near_duplicates(rows).collect()
    assert len(got) == rows.count() and {r["component_id"] for r in got if r["doc_id"] in (None, 70)} == {70}


# ---------------------------------------------------------------- very long texts


def long_lines(n, spread):
    rng = random.Random(1)
    return "\n".join(f"line number {rng.randrange(spread)} of a very long text" for _ in range(n))


def test_line_dedup_of_a_very_long_text(spark):
    body = long_lines(200_000, 150_000)
    began = time.perf_counter()
    got = line_dedup.line_dedup(docs(spark, [body, "x"]).repartition(2)).collect()
    assert time.perf_counter() - began < 60 and sorted(r["n_lines"] for r in got) == [1, 200_000]
    twice = "\n".join(f"another line with the number {i} in it" for i in range(30_000))
    removed = {r["doc_id"]: r["n_removed"] for r in line_dedup.line_dedup(docs(spark, [twice, twice + "\nend"])).collect()}
    assert removed == {0: 0, 1: 30_000}


def test_very_long_texts_elsewhere(spark):
    many = "mit license and some words " * 20_000
    began = time.perf_counter()
    row = license_scan.scan_licenses(docs(spark, [many])).first()
    assert row["n_base"] == 20_000 and row["n_words"] == 100_000 and row["last_word"] == 5 * 19_999
    items = spark.createDataFrame([(1, " ".join(f"w{i}" for i in range(20)))], "item_id long, text string")
    text = " ".join(f"z{i}" for i in range(100_000)) + " " + " ".join(f"w{i}" for i in range(20))
    hit = decontamination.decontaminate(docs(spark, [text]), items).first()
    assert hit["n_hit"] == 20 and hit["n_items"] == 1
    turns = spark.createDataFrame([(1, i, "assistant" if i % 2 else "user", f"text {i}") for i in range(20_000)], "conv_id long, turn long, role string, text string")
    out = chat_format.format_conversations(chat_format.linear_tree(turns)).first()
    assert len(chat_format.parse(out["formatted"])) == 20_000 and len(out["loss_spans"]) == 10_000
    assert exact_dedup.exact_dedup(docs(spark, [many, many + " "])).select("keep_id").distinct().count() == 1
    assert time.perf_counter() - began < 150


def test_clashing_columns_of_chat(spark):
    turns = spark.createDataFrame([(1, 0, "user", "q", 5, "x", 1.0), (1, 1, "assistant", "a", 5, "x", 1.0)], "conv_id long, turn long, role string, text string, id long, head string, total double")
    out = chat_format.format_conversations(chat_format.linear_tree(turns)).first()
    assert chat_format.parse(out["formatted"]) == [("user", "q"), ("assistant", "a")]


# ---------------------------------------------------------------- pipeline


def test_pipeline_stages_on_empty_and_odd_tables(spark):
    import corpus_pipeline

    columns = ["doc_id", "text", "lang", "source", "n_chars"]
    for rows in (docs(spark, ["x"]).limit(0), docs(spark, [*ODD, (3, "a"), (None, "some words here")]).withColumn("lang", F.lit(None).cast("string"))):
        current = rows.select(*columns)
        for name, stage in corpus_pipeline.STAGES:
            current = stage(spark, current, "/root/testdata/sf0.001")
            if name != "best_fit_packing":
                assert current.columns == columns
        current.collect()


def test_language_stage_fills_languages(spark):
    rows = spark.createDataFrame([(i, "the cat and the dog", "en") for i in range(20)] + [(i, "der hund und die katze", "de") for i in range(20, 40)] + [(90, "the dog", None), (91, "12", "en"), (92, None, None)], "doc_id long, text string, lang string")
    got = {r["doc_id"]: r["lang"] for r in language_id.stage(spark, rows, "").collect()}
    assert got[90] == "en" and 91 not in got and 92 not in got and len(got) == 41


def test_pipeline_equals_its_stages_by_brute_force(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    texts = {r["doc_id"]: r["text"] or "" for r in table(spark, "documents", sf).collect()}
    alive = {i: t for i, t in texts.items() if any(c.isalpha() for w in re.findall(r"[^\W\d_]+", t) for c in w)}
    groups = defaultdict(list)
    for i, t in alive.items():
        groups[re.sub("[\x20\x09-\x0d]", "", t)].append((-len(t), i))
    alive = {min(g)[1]: texts[min(g)[1]] for g in groups.values()}
    alive = {i: alive[i] for i, _, _, kept in brute_components(sorted(alive.items())) if kept}
    windows = set()
    for r in table(spark, "benchmark", sf).collect():
        w = words_of(r["text"])
        windows |= {tuple(w[s : s + min(13, len(w))]) for s in range(len(w) - min(13, len(w)) + 1)} if w else set()
    sizes = {len(w) for w in windows}
    for i, t in list(alive.items()):
        w, hit = words_of(t), set()
        for n in sizes:
            for s in range(len(w) - n + 1):
                if tuple(w[s : s + n]) in windows:
                    hit |= set(range(s, s + n))
        if hit and 20 * len(hit) >= len(w):
            del alive[i]
    rows = corpus_pipeline.run(spark, sf).collect()
    assert {r["doc_id"] for r in rows} == set(alive)
    tokens = Counter()
    for r in rows:
        tokens[r["doc_id"]] += r["length"]
    assert all(tokens[i] == len(packing.token_ids(t)) for i, t in itertools.islice(alive.items(), 40))


def test_folding_helpers():
    assert fold("AbÉ") == "abÉ"
