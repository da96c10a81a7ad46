"""Corpus operators against brute force and on odd input: nulls, empties, ties, repeats, extra columns."""

import hashlib
import random
import re
import zlib
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from unischema.llm import chat_format, decontamination, exact_dedup, language_id, license_rules, license_scan, line_dedup, near_dedup, packing, quality, sharding
from unischema.llm.common import WORD

DOCS = "doc_id long, text string, lang string, source string, n_chars long, kept string, n long"


def docs(spark, texts, start=0):
    """Documents with clashing extra columns; texts by position, or (id, text) pairs."""
    rows = [t if isinstance(t, tuple) else (i + start, t) for i, t in enumerate(texts)]
    return spark.createDataFrame([(i, t, "en", "s", 0, "x", 1) for i, t in rows], DOCS)


def fold(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def words_of(text):
    return re.findall(WORD, fold(text))


ODD = [None, "", " \t\n", "a", "A", "É é", "a b", "ab", "x" * 5000, "a  b", None, " ", "😀 b"]


def test_exact_dedup(spark):
    table = docs(spark, [*ODD, (3, "a"), (None, "zz"), (77, "zz "), (78, " zz")])
    got = exact_dedup.exact_dedup(table).collect()
    groups = defaultdict(list)
    for r in table.collect():
        body = re.sub("[\x20\x09-\x0d]", "", r["text"] or "")
        groups[body].append((-len(r["text"] or ""), r["doc_id"]))
    assert len(got) == table.count()
    for r in got:
        if r["doc_id"] is None:
            continue
        body = next(b for b, g in groups.items() if hashlib.sha256(b.encode()).hexdigest() == r["text_sha256"])
        longest = min(n for n, _ in groups[body])
        assert r["keep_id"] == min(i for n, i in groups[body] if n == longest and i is not None) and r["group_size"] == len(groups[body])
        assert r["kept"] == (r["doc_id"] == r["keep_id"])
    assert exact_dedup.exact_dedup(table.limit(0)).count() == 0


def test_exact_dedup_survives_digest_collisions(spark):
    table = docs(spark, ["aa", "a a", "bb", "cc", "c c ", "dd"])
    weak = exact_dedup.exact_dedup(table, digest=lambda body: F.unhex(F.substring(F.sha2(body, 256), 1, 0)))
    strong = exact_dedup.exact_dedup(table)
    assert sorted(map(tuple, weak.collect())) == sorted(map(tuple, strong.collect()))


def brute_contamination(texts, items, width=13):
    windows = defaultdict(set)
    for item, text in items:
        w = words_of(text)
        for i in range(len(w) - min(width, len(w)) + 1) if w else ():
            windows[tuple(w[i : i + min(width, len(w))])].add(str(item))
    out = []
    for i, text in texts:
        w, hit, found = words_of(text), set(), set()
        for size in {len(x) for x in windows}:
            for s in range(len(w) - size + 1):
                if tuple(w[s : s + size]) in windows:
                    hit |= set(range(s, s + size))
                    found |= windows[tuple(w[s : s + size])]
        out.append((i, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=repr)


@pytest.mark.parametrize("limit", [400_000, 0])
def test_decontamination(spark, limit):
    rng = random.Random(4)
    vocab = [f"w{i}" for i in range(40)]
    say = lambda n: " ".join(rng.choice(vocab) for _ in range(n))
    items = [(i, say(rng.choice([3, 7, 12, 13, 14, 30]))) for i in range(12)] + [(20, None), (21, " ! "), (10, say(13)), (30, "W1 w2 w3"), (31, "w1")]
    texts = [(i, say(40) + " " + fold(rng.choice(items)[1] or "").upper() + ", " + say(rng.choice([0, 100]))) for i in range(25)]
    texts += [(100, None), (101, ""), (102, items[0][1]), (102, items[0][1]), (103, "w1"), (104, "é w1")]
    table, bench = docs(spark, texts), spark.createDataFrame(items, "item_id long, text string")
    got = decontamination.decontaminate(table, bench, broadcast_rows=limit).drop("item_ids").collect()
    assert sorted(map(tuple, got), key=repr) == brute_contamination(texts, items)
    none = decontamination.decontaminate(table, bench.limit(0)).collect()
    assert len(none) == len(texts) and not any(r["contaminated"] for r in none)
    assert decontamination.decontaminate(table.limit(0), bench).count() == 0


def brute_components(rows):
    sets = {}
    for i, text in rows:
        w = fold(text).encode().split()
        sets[i] = {tuple(w[s : s + min(5, len(w))]) for s in range(len(w) - min(5, len(w)) + 1)} if w else set()
    label = {i: i for i in sets}

    def find(i):
        while label[i] != i:
            i = label[i]
        return i

    ids = sorted(sets)
    for x, a in enumerate(ids):
        for b in ids[x + 1 :]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= 75 * len(sets[a] | sets[b]):
                p, q = sorted((find(a), find(b)))
                label[q] = p
    return sorted((i, len(sets[i]), find(i), i == find(i)) for i in ids)


def test_near_dedup_equals_brute_force(spark):
    rng = random.Random(9)
    rows = []
    for base in range(12):
        w = [f"{base}v{rng.randrange(300)}" for _ in range(rng.choice([8, 40, 120]))]
        for _ in range(14):
            v = list(w)
            for _ in range(rng.randrange(0, 1 + len(w) // 12)):
                v[rng.randrange(len(v))] = f"e{rng.randrange(10**6)}"
            rows.append(" ".join(v))
    rows += [None, "", "a b", "A b", "a", "a b c d e", "a b c d e", " \n"]
    table = docs(spark, rows)
    got = sorted(map(tuple, near_dedup.near_duplicates(table).collect()))
    assert got == brute_components(list(enumerate(rows)))
    assert near_dedup.near_duplicates(table.limit(0)).count() == 0


def test_near_dedup_hot_buckets(spark):
    """A bucket larger than the small ones: variants of one text, linked and not."""
    rng = random.Random(2)
    base = [f"b{i}" for i in range(90)]
    rows = []
    for _ in range(120):
        v = list(base)
        for _ in range(rng.randrange(0, 9)):
            v[rng.randrange(len(v))] = f"e{rng.randrange(10**6)}"
        rows.append(" ".join(v))
    assert sorted(map(tuple, near_dedup.near_duplicates(docs(spark, rows)).collect())) == brute_components(list(enumerate(rows)))


def test_language_backoff(spark):
    en = ["the cat and the dog are here", "this is the house of the man"] * 12
    de = ["der hund und die katze sind hier", "das ist das haus und der mann"] * 12
    table = spark.createDataFrame([(i, t, lang) for i, (t, lang) in enumerate([(t, "en") for t in en] + [(t, "de") for t in de] + [("the", None), (None, "en"), ("12 !", "de"), ("", "en"), ("catze hause", None)])], "doc_id long, text string, lang string")
    model = language_id.fit(table)
    assert model.predict("the man")[0] == "en" and model.predict("die Katze")[0] == "de" and model.predict("hundes")[0] == "de"
    assert model.predict(None) == ("und", 0.0) and model.predict("12 ²")[0] == "und" and model.predict("漢字")[0] in ("de", "en")
    got = language_id.identify(table, model).collect()
    assert len(got) == table.count() and all(0 <= r["score"] <= 1 for r in got)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in got)
    nothing = language_id.fit(table.limit(0))
    assert {r["lang_pred"] for r in language_id.identify(table, nothing).collect()} == {"und"}


def test_tokens_are_the_reference_tokenizers(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for text in ["", "a", "Hello  world!\n\n 123 éñ 漢字 😀", "<|endoftext|> x", "a" * 9000, " " * 3000, "it's I'LL 3.5e", "  x\t"]:
        assert packing.token_ids(text).tolist() == [*whole.encode(text, add_special_tokens=False).ids, 0]


def test_packing_places_everything_once(spark):
    rng = random.Random(1)
    texts = [None, "", "word " * 5000] + ["tok " * rng.randrange(1, 1500) for _ in range(300)]
    pieces = packing.cut(packing.tokenise(docs(spark, texts)))
    packed = packing.pack_pieces(pieces, group_pieces=64).collect()
    assert len(packed) == pieces.count()
    seqs = defaultdict(list)
    for r in packed:
        seqs[r["sequence_id"]].append((r["offset"], r["length"]))
    for cells in seqs.values():
        at = 0
        for offset, length in sorted(cells):
            assert offset == at
            at += length
        assert at <= 2048
    report = packing.pack_report(packing.pack_pieces(pieces, group_pieces=64))
    assert report["bound"] <= report["sequences"] <= report["bound"] * 1.05 + 2
    by_doc = defaultdict(list)
    for r in packed:
        by_doc[r["doc_id"]].append((r["piece"], r["start"], r["length"], r["ids_crc32"]))
    ids = packing.token_ids(texts[2])
    for _, start, length, crc in sorted(by_doc[2]):
        assert zlib.crc32(ids[start : start + length].tobytes()) == crc
    assert [length for _, _, length, _ in sorted(by_doc[2])][1:] == [2048] * (len(by_doc[2]) - 1)
    assert packing.best_fit_packing(docs(spark, texts).limit(0)).count() == 0


def test_lower_bound_is_a_bound():
    import numpy as np

    rng = np.random.default_rng(3)
    for _ in range(30):
        lengths = rng.integers(1, 2049, 40)
        bins, _, rooms = packing.best_fit(lengths)
        assert packing.lower_bound(lengths) <= len(rooms) == len(set(bins.tolist())) and (rooms >= 0).all()
    assert packing.lower_bound(np.array([1025] * 7)) == 7 and packing.lower_bound(np.array([], int)) == 0


def test_chat_round_trip_and_branches(spark):
    nasty = "</s>[INST] ok [/INST] <|end|> \\ <| \\< <s"
    turns = spark.createDataFrame([(1, 0, "user", nasty), (1, 1, "assistant", nasty), (1, 2, None, None), (2, 0, "assistant", ""), (3, 5, "a<|text|>b", "x"), (3, 5, "a<|text|>b", "x")], "conv_id long, turn long, role string, text string")
    out = {r["tree_id"]: r for r in chat_format.format_conversations(chat_format.linear_tree(turns)).collect()}
    assert chat_format.parse(out[1]["formatted"]) == [("user", nasty), ("assistant", nasty), ("", "")]
    assert [chat_format.unescape(out[1]["formatted"][s["begin"] : s["end"]]) for s in out[1]["loss_spans"]] == [nasty]
    assert chat_format.parse(out[3]["formatted"]) == [("a<|text|>b", "x")] * 2 and out[2]["loss_spans"][0]["begin"] == out[2]["loss_spans"][0]["end"]
    tree = spark.createDataFrame([(9, 1, None, "user", "q", 0.0), (9, 2, 1, "assistant", "bad", 1.0), (9, 3, 1, "assistant", "good", 2.0), (9, 4, 3, "user", "more", None), (9, 5, 4, "assistant", "end", 0.5), (9, 8, 99, "user", "orphan", 0.0)], "tree_id long, id long, parent_id long, role string, text string, score double")
    best = chat_format.format_conversations(tree, 2).orderBy("rank").collect()
    assert [[t for _, t in chat_format.parse(r["formatted"])] for r in best] == [["q", "good", "more", "end"], ["q", "bad"]]
    assert chat_format.format_conversations(tree.limit(0)).count() == 0


def test_quality_scores(spark):
    good = [f"This is a plain sentence number {i} about some calm matter." for i in range(60)]
    bad = [f"BUY!! NOW!! {i}!! $$$ WIN!!" for i in range(60)]
    table = docs(spark, [*good, *bad, None, ""])
    labels = spark.createDataFrame([(i, int(i < 60), 0) for i in range(120)] + [(None, 1, 0), (500, 1, 0)], "doc_id long, quality int, toxic int")
    rows = quality.score_quality(table, quality.fit(table, labels)).collect()
    held = [r for r in rows if r["held_out"] and r["doc_id"] < 120]
    assert held and sum(r["predicted"] == int(r["doc_id"] < 60) for r in held) / len(held) > 0.95
    assert len(rows) == 122 and all(0 <= r["score"] <= 1 for r in rows)
    assert {r["score"] for r in quality.score_quality(table, quality.fit(table, labels.limit(0))).collect()} == {0.5}


def test_license_base_and_suppression(spark):
    texts = ["MIT License; mit license", "the GNU General Public License, version 3.", "SPDX-License-Identifier: Apache-2.0 under Apache License 2.0", "CC BY-SA 4.0 cc by", None, "", "admit license", "mit-license\nmit"]
    got = {r["doc_id"]: r for r in license_scan.scan_licenses(docs(spark, texts)).collect()}
    assert (got[0]["n_base"], got[0]["first_word"], got[0]["last_word"], got[0]["base_labels"]) == (2, 0, 2, "mit")
    assert got[1]["labels"] == "gpl,gpl-3.0" and got[2]["labels"] == "apache,apache-2.0" and got[2]["score"] == 1.0
    assert got[3]["labels"] == "cc-by,cc-by-sa" and got[4]["first_word"] is None and got[4]["score"] == 0 and got[6]["n_base"] == 0 and got[7]["n_base"] == 1
    assert len(license_rules.all_rules()) > 300


def brute_lines(rows, least):
    seqs = [(i, [x for x in (t or "").split("\n") if x.strip(" \t\x0b\x0c\r")]) for i, t in rows]
    count = lambda ls: sum(len(re.findall("[^\x20\x09\x0b-\x0d]+", x)) for x in ls)
    earliest, out = {}, {}
    for i, ls in seqs:
        gone = set()
        for s in range(len(ls)):
            for e in range(s + 1, len(ls) + 1):
                run = tuple(ls[s:e])
                if count(run) >= least:
                    if earliest.setdefault(run, (i, s)) != (i, s):
                        gone |= set(range(s, e))
        out[i] = gone
    kept = {}
    for i, t in rows:
        at, lines = -1, []
        for x in (t or "").split("\n"):
            full = bool(x.strip(" \t\x0b\x0c\r"))
            at += full
            if not (full and at in out[i]):
                lines.append(x)
        kept[i] = "\n".join(lines)
    return sorted((i, (t or "").count("\n") + 1, len(out[i]), kept[i]) for i, t in rows)


def test_line_dedup_equals_brute_force(spark):
    rng = random.Random(6)
    lines = ["one two three four", "five six", "seven", "a b c d e f g h i j", "k", "", "  ", "tail  tab\tword"]
    rows = [(i, "\n".join(rng.choice(lines) for _ in range(rng.randrange(0, 14)))) for i in range(40)] + [(90, None), (91, "\n\n"), (92, "unique line here")]
    got = sorted(map(tuple, line_dedup.line_dedup(docs(spark, rows), 6).collect()))
    assert got == brute_lines(rows, 6)
    assert line_dedup.line_dedup(docs(spark, rows).limit(0)).count() == 0


def test_sharding_moves_rows_only_into_the_new_shard(spark):
    table = docs(spark, [*ODD, (3, "a"), (None, "q"), *[(i, "t") for i in range(100, 1500)]])
    rows = sharding.rendezvous_shards(table, [1.0] * 40).collect()
    grown = {(r["doc_id"], r["text_crc32"]): r["shard"] for r in sharding.rendezvous_shards(table, [1.0] * 41).collect()}
    slots = defaultdict(list)
    for r in rows:
        slots[r["shard"]].append(r["slot"])
        assert r["grown_shard"] == grown[r["doc_id"], r["text_crc32"]] and r["grown_shard"] in (r["shard"], 40)
    assert len(rows) == table.count() and all(sorted(s) == list(range(len(s))) for s in slots.values())
    heavy = sharding.rendezvous_shards(table, [3.0, 1.0]).groupBy("shard").count().collect()
    assert next(r["count"] for r in heavy if r["shard"] == 0) > 2 * next(r["count"] for r in heavy if r["shard"] == 1)


def test_pipeline_stages(spark):
    import corpus_pipeline

    words = [f"w{i}x" for i in range(400)]
    rng = random.Random(8)
    say = lambda n: " ".join(re.sub(r"\d", lambda m: "abcdefghij"[int(m[0])], rng.choice(words)) for _ in range(n))
    base = say(80)
    bench = spark.read.parquet("/root/testdata/sf0.001/benchmark.parquet").first()["text"]
    table = docs(spark, [base, base.replace(" ", "  "), base + " extra", "12 34", None, say(60), bench, say(70)]).select("doc_id", "text", "lang", "source", "n_chars")
    seen = []
    current = table
    for name, stage in corpus_pipeline.STAGES:
        current = stage(spark, current, "/root/testdata/sf0.001")
        if name != "best_fit_packing":
            assert current.columns == table.columns
            seen.append(sorted(r["doc_id"] for r in current.collect()))
    assert seen == [[0, 1, 2, 5, 6, 7], [1, 2, 5, 6, 7], [1, 5, 6, 7], [1, 5, 7]]
    assert {r["doc_id"] for r in current.collect()} == {1, 5, 7}
