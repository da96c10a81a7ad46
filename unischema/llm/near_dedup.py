"""Near-duplicate components: MinHash signatures met by a multi-index Hamming join, then exact links.

Each set of shingles gets a signature of ``SYMBOLS`` symbols of b = 32 bits. All pairs within a Hamming
distance of ``DISTANCE`` symbols meet: the signature is split into ``CHUNKS`` chunks, and by the
pigeonhole principle two such signatures differ in at most one symbol of some chunk, as
``DISTANCE < 2 * CHUNKS``. Each chunk is indexed once for each symbol left out (its allowed error), so
equal keys are exactly the chunks within one error. The distance is then tested on whole signatures,
of whose symbols ``SHORT`` bits each are carried along (equal symbols stay equal, so none is lost).
A pair at the similarity of 0.75 differs in 8.25 of 33 symbols in the mean; that it differs in over 21
has a probability of 5.5e-7.

Two sketches pass over pairs that cannot be links before any set is fetched:

* a *parity bitmap* of ``PARITY`` bits, in which each shingle flips the bit of its hash. The bitmaps of
  two sets differ in at most as many bits as the sets do in shingles, and 100 * i >= 75 * u allows a
  difference of a seventh of the two sizes: for short texts this test is nearly exact and drops no link.
  Bits of long texts collide, so there ``PARITY_SLACK`` above the expected number is allowed
  (probability of a miss below 7e-10 by Hoeffding's bound), wherever that is less;
* ``SKETCH`` more symbols of b = 4 bits, which hold for texts of any length. At the similarity of 0.75
  pairs differ in 45 of them in the mean with a deviation of 5.9, and in more than ``SKETCH_DISTANCE``
  with a probability below 3e-9.

No bucket is ever expanded into all its pairs:

1. documents with the same set of shingles are one class, and only its representative is indexed;
2. *stars*: in every bucket each member is compared with two centres, and verified links are closed
   into components;
3. members of a bucket that are not in the component of its centre are compared with the members of
   other components inside the join (size, sketch and signature tests are part of the join condition,
   so hardly any pair leaves it that is not a link), in as many tasks as AQE's skew splitting makes of
   a hot bucket.

Every link is confirmed on the full sets; the result is exactly the components of the link graph,
up to the chances above. Sets are shuffled only for documents that have candidates: a fixed-size
bitmap of their ids (``FILTER_BITS``) removes nearly all others before their texts reach Python.

Components of up to ``LOCAL_LINKS`` links are closed in one executor task; more of them by alternating
star steps, in which a hub is only joined by equality and reduced by a minimum. Both are exact.

Defined results: documents without words (null, empty, blank) have no shingles, are linked with
nothing and stay. A null id is kept if it is its own component's id (null counts as larger than
any id). Rows that repeat an id and text get the same answer; ties between equal ids do not matter.
Columns beyond ``doc_id`` and ``text`` are ignored; an empty table gives an empty result. Texts are
read whole, also very long ones: a text's shingles are hashed in blocks of bounded size.
"""

from __future__ import annotations

import string
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unischema.llm.common import Workspace, arrow_ready, cut, drop_rows, read_table

SHINGLE = 5
#: Link at 100 * intersection >= PERCENT * union.
PERCENT = 75
CHUNKS, CHUNK = 11, 3
SYMBOLS = CHUNKS * CHUNK
DISTANCE = 2 * CHUNKS - 1
#: Symbols of the sketch and the distance allowed; four bits each, in longs of so many.
SKETCH, SKETCH_DISTANCE, CELLS = 192, 81, 16
#: Bits of the parity bitmap, and how far above the expected number of unequal ones a pair may be.
PARITY, PARITY_SLACK = 1024, 104
#: Bits kept of each symbol for the test of the signatures' distance, in fields of one bit more.
SHORT, SHORTS = 14, 4
#: Bits of the filter on ids with candidates; fixed, whatever the input.
FILTER_BITS = 1 << 23
#: Links that one task closes into components (16 bytes each); beyond it the star steps do.
LOCAL_LINKS = 2_000_000
#: Labelled nodes up to which the labels are broadcast (16 bytes each).
LABEL_ROWS = 500_000

_FOLD = bytes.maketrans(string.ascii_uppercase.encode(), string.ascii_lowercase.encode())
_ODD = np.random.default_rng(20240229).integers(1, 1 << 63, size=SYMBOLS + SKETCH, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_PLACES = _ODD[:8]
_NIBBLES = np.arange(CELLS, dtype=np.uint64) * np.uint64(4)
_FIELDS = np.arange(SHORTS, dtype=np.uint64) * np.uint64(SHORT + 1)
_CACHE_WORDS = 200_000
_LOW = (1 << 64) - 1


def _mix(x: np.ndarray) -> np.ndarray:
    """A published 64-bit finaliser (xor-shift and multiply), element by element."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Shingler:
    """Sets of 64-bit shingle hashes; remembers the hashes of words."""

    def __init__(self) -> None:
        import xxhash

        self._hash = xxhash.xxh3_64_intdigest
        self._known: dict[bytes, int] = {}

    def __call__(self, text: str | None) -> np.ndarray:
        """The sorted distinct shingle hashes of one text."""
        found = (text or "").encode("utf-8", "surrogatepass").translate(_FOLD).split()
        if not found:
            return np.empty(0, np.uint64)
        known = self._known
        hashes = list(map(known.get, found))
        if None in hashes:
            if len(known) > _CACHE_WORDS:
                known.clear()
            for w in found:
                if w not in known:
                    known[w] = self._hash(w)
            hashes = list(map(known.get, found))
        words = np.array(hashes, np.uint64)
        width = min(SHINGLE, len(words))
        runs = np.full(len(words) - width + 1, width, np.uint64)
        for j in range(width):
            runs += words[j : len(words) - width + 1 + j] * _PLACES[j]
        return np.unique(_mix(runs))


def _least(shingles: np.ndarray, factors: np.ndarray) -> np.ndarray:
    """The least product with each odd factor (mod 2^64), mixed: one min-hash for each factor.

    The shingles are outputs of a strong hash, so multiplication alone orders them anew.
    """
    least = np.full(len(factors), np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 512):
        np.minimum(least, (shingles[None, at : at + 512] * factors[:, None]).min(1), out=least)
    return _mix(least)


def signature(shingles: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``SYMBOLS`` symbols of 32 bits; and, as longs, the shortened symbols, the sketch and the parity bitmap."""
    least = _least(shingles, _ODD)
    symbols = least[:SYMBOLS].astype(np.uint32).view(np.int32)
    short = np.zeros(-(-SYMBOLS // SHORTS) * SHORTS, np.uint64)
    short[:SYMBOLS] = least[:SYMBOLS] & np.uint64((1 << SHORT) - 1)
    cells = (least[SYMBOLS:] & np.uint64(15)).reshape(-1, CELLS) << _NIBBLES
    flips = np.bincount((shingles >> np.uint64(40)).astype(np.int64) % PARITY, minlength=PARITY) & 1
    longs = (np.bitwise_or.reduce(short.reshape(-1, SHORTS) << _FIELDS, axis=1), np.bitwise_or.reduce(cells, axis=1), np.packbits(flips.astype(np.uint8), bitorder="little").view(np.uint64))
    return symbols, np.concatenate(longs).view(np.int64)


_SIG_COLUMNS = [f"s{i}" for i in range(SYMBOLS)]
_SHORT_COLUMNS = [f"b{i}" for i in range(-(-SYMBOLS // SHORTS))]
_SKETCH_COLUMNS = [f"k{i}" for i in range(SKETCH // CELLS)]
_PARITY_COLUMNS = [f"p{i}" for i in range(PARITY // 64)]
#: What a bucket's rows carry of their signature.
_CARRIED = [*_SHORT_COLUMNS, *_SKETCH_COLUMNS, *_PARITY_COLUMNS]


def signatures(docs: DataFrame) -> DataFrame:
    """``doc_id, n, d0, d1`` (a 128-bit digest of the set) and the symbols; null where the set is empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        shingle = Shingler()
        for batch in batches:
            sizes, digests, symbols, sketches = [], [], [], []
            for text in batch.column(1):
                found = shingle(text.as_py())
                sizes.append(len(found))
                if len(found):
                    whole = xxhash.xxh3_128_intdigest(found.tobytes())
                    digests.append((whole >> 64, whole & _LOW))
                    own, more = signature(found)
                    symbols.append(own)
                    sketches.append(more)
                else:
                    digests.append((0, 0))
                    symbols.append(np.zeros(SYMBOLS, np.int32))
                    sketches.append(np.zeros(len(_CARRIED), np.int64))
            matrix = np.array(symbols, np.int32).reshape(-1, SYMBOLS)
            pair = np.array(digests, np.uint64).reshape(-1, 2).view(np.int64)
            columns = [batch.column(0), pa.array(sizes, pa.int64()), pa.array(pair[:, 0]), pa.array(pair[:, 1])]
            columns += [pa.array(np.ascontiguousarray(matrix[:, i])) for i in range(SYMBOLS)]
            bits = np.array(sketches, np.int64).reshape(-1, len(_CARRIED))
            columns += [pa.array(np.ascontiguousarray(bits[:, i])) for i in range(len(_CARRIED))]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n", "d0", "d1", *_SIG_COLUMNS, *_CARRIED])

    symbols = ", ".join([f"{s} int" for s in _SIG_COLUMNS] + [f"{s} long" for s in _CARRIED])
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, f"doc_id long, n long, d0 long, d1 long, {symbols}")


def keys_of() -> Column:
    """An array of a row's keys: each chunk with each of its symbols left out."""
    keys = []
    for chunk in range(CHUNKS):
        own = [F.col(f"s{chunk * CHUNK + i}") for i in range(CHUNK)]
        for out in range(CHUNK):
            keys.append(F.xxhash64(F.lit(chunk * CHUNK + out), *[c for i, c in enumerate(own) if i != out]))
    return F.array(*keys)


def _near(a: str, b: str) -> Column:
    """Sizes allow the similarity, and bitmaps, sketches and signatures are within their distances.

    Kept to few operations on longs, so that the generated code stays small enough to be compiled.
    """
    low, high = F.least(F.col(f"{a}.n"), F.col(f"{b}.n")), F.greatest(F.col(f"{a}.n"), F.col(f"{b}.n"))

    def apart(columns: list[str], unequal) -> Column:
        return sum((F.bit_count(unequal(F.col(f"{a}.{s}").bitwiseXOR(F.col(f"{b}.{s}")))) for s in columns), F.lit(0))

    def cells(x: Column) -> Column:
        """A bit for each cell of four bits that is not zero."""
        halves = x.bitwiseOR(F.shiftrightunsigned(x, 1))
        return halves.bitwiseOR(F.shiftrightunsigned(halves, 2)).bitwiseAND(F.lit(0x1111111111111111))

    def fields(x: Column) -> Column:
        """A bit for each field that is not zero, by a carry into its spare bit."""
        most, spare = (sum(v << (i * (SHORT + 1)) for i in range(SHORTS)) for v in ((1 << SHORT) - 1, 1 << SHORT))
        return (x + F.lit(most)).bitwiseAND(F.lit(spare))

    lacking = (low + high) * (100 - PERCENT) / (100 + PERCENT)
    flipped = F.least(lacking, (1 - F.exp(lacking * (-2 / PARITY))) * (PARITY / 2) + PARITY_SLACK)
    close = apart(_PARITY_COLUMNS, lambda x: x) <= flipped
    return (low * 100 >= high * PERCENT) & close & (apart(_SKETCH_COLUMNS, cells) <= SKETCH_DISTANCE) & (apart(_SHORT_COLUMNS, fields) <= DISTANCE)


def components(links: DataFrame, cut=cut, local_links: int = LOCAL_LINKS) -> DataFrame:
    """``(node, label)``: the least node reachable by ``(a, b)`` links, for every node of a link."""
    if links.count() <= local_links:
        return cut(links.coalesce(1).mapInArrow(_close, "node long, label long"))
    return _star_steps(links, cut)


def _close(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All of a bounded number of links in one task: labels sink along links, then along themselves."""
    parts = [np.stack([b.column(0).to_numpy(), b.column(1).to_numpy()]) for b in batches]
    ends = np.concatenate([np.empty((2, 0), np.int64), *parts], axis=1)
    nodes, places = np.unique(ends, return_inverse=True)
    a, b = places.reshape(ends.shape)
    label = np.arange(len(nodes))
    while True:
        least = np.minimum(label[a], label[b])
        sunk = label.copy()
        for side in (a, b, label[a], label[b]):
            np.minimum.at(sunk, side, least)
        sunk = sunk[sunk]
        if np.array_equal(sunk, label):
            break
        label = sunk
    yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(nodes[label])], ["node", "label"])


def _star_steps(links: DataFrame, cut) -> DataFrame:
    """Alternating large-star and small-star steps; no neighbourhood is gathered anywhere."""
    edges = cut(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    mark = None
    while True:
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        floor = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(floor, "u").select(F.explode(F.array(F.struct(F.greatest("v", "m").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e")).select("e.*")
        edges = cut(small.where("u <> v").distinct())
        now = edges.agg(F.count(F.lit(1)), F.sum(F.pmod(F.xxhash64("u", "v"), F.lit(1 << 40)))).first()
        if now == mark:
            break
        mark = now
    roots = edges.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("label"))
    return edges.select(F.col("u").alias("node"), F.col("v").alias("label")).unionByName(roots.join(edges.select(F.col("u").alias("node")), "node", "left_anti"))


def _place() -> Column:
    return F.pmod(F.xxhash64("id"), F.lit(FILTER_BITS))


def _bitmap(ids: DataFrame) -> DataFrame:
    """``at, bits``: the longs of a bitmap of ``FILTER_BITS`` bits; no more than ``FILTER_BITS / 64`` rows."""
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), (_place() % 64).cast("int"))
    return ids.select((_place() / 64).cast("long").alias("at"), bit.alias("bit")).groupBy("at").agg(F.bit_or("bit").alias("bits"))


def shingle_sets(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """``(id, shingles)`` of the documents in ``ids`` and of a few others."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle = Shingler()
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                sets = [shingle(t.as_py()).view(np.int64) for t in part.column(1)]
                ends = np.cumsum([0, *map(len, sets)]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(sets)))], ["id", "shingles"])

    numbered = docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("id"), "text")
    placed = numbered.withColumn("at", (_place() / 64).cast("long")).join(F.broadcast(_bitmap(ids)), "at")
    chosen = placed.where(F.getbit("bits", (_place() % 64).cast("int")) == 1)
    return chosen.select("id", "text").mapInArrow(run, "id long, shingles array<long>")


def confirmed(pairs: DataFrame, docs: DataFrame, cut=cut) -> DataFrame:
    """The pairs ``(a, b)`` at the similarity or above, by their full sets.

    The sets are written once: both joins then read plain exchanges, of which AQE can split a hot centre.
    """
    pairs = cut(pairs)
    ids = pairs.select(F.explode(F.array("a", "b")).alias("id"))
    sets = cut(shingle_sets(docs, ids).dropDuplicates(["id"]))
    left = sets.select(F.col("id").alias("a"), F.col("shingles").alias("x"))
    right = sets.select(F.col("id").alias("b"), F.col("shingles").alias("y"))
    shared = F.size(F.array_intersect("x", "y"))
    linked = shared * 100 >= (F.size("x") + F.size("y") - shared) * PERCENT
    return pairs.join(left, "a").join(right, "b").where(linked).select("a", "b")


def near_duplicates(docs: DataFrame, local_links: int = LOCAL_LINKS, label_rows: int = LABEL_ROWS) -> DataFrame:
    """``doc_id, n_shingles, component_id, kept`` for each row of ``docs``."""
    arrow_ready(docs.sparkSession)
    work = Workspace(docs.sparkSession)
    try:
        signed = work.cut(signatures(docs))
        symbols = [*_SIG_COLUMNS, *_CARRIED]
        classes = signed.where("n > 0").groupBy("d0", "d1", "n").agg(F.min("doc_id").alias("id"), *[F.min(s).alias(s) for s in symbols])
        classes = work.cut(classes)
        buckets = work.cut(_buckets(classes.where(F.col("id").isNotNull())))
        links = work.cut(confirmed(_star_pairs(buckets), docs, work.cut))
        labels = components(links, work.cut, local_links)
        found = work.cut(confirmed(_cross_pairs(buckets, labels, label_rows), docs, work.cut))
        if not found.isEmpty():
            labels = components(links.unionByName(found), work.cut, local_links)
        named = classes.join(_bounded(labels, label_rows), classes["id"] == labels["node"], "left").select("d0", "d1", "n", F.coalesce("label", "id").alias("component"))
        return cut(_label_rows(signed.select("doc_id", "d0", "d1", "n"), named))
    finally:
        work.clear()


def _bounded(labels: DataFrame, most: int) -> DataFrame:
    """``labels``, broadcast if they are counted to be few."""
    return F.broadcast(labels) if labels.count() <= most else labels


def _buckets(classes: DataFrame) -> DataFrame:
    """``key, slot, id, c0, c1`` and the symbols, for buckets of two members at least.

    The centres are the least id and one by a hash that differs by bucket.
    """
    keyed = classes.select("id", F.posexplode(keys_of()).alias("slot", "key"))
    centres = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("many"), F.min("id").alias("c0"), F.min(F.xxhash64("id", "key")).alias("h1")).where("many > 1").drop("many")
    return keyed.join(centres, "key").withColumn("centre", F.when(F.col("id") == F.col("c0"), 0).when((F.col("slot") % CHUNK == 0) & (F.xxhash64("id", "key") == F.col("h1")), 1)).drop("h1").join(classes.select("id", "n", *_CARRIED), "id")


def _known(buckets: DataFrame) -> DataFrame:
    """The buckets with columns that are known not to be null, which shortens the code of the joins."""
    return buckets.withColumns({c: F.coalesce(c, F.lit(0).cast("long")) for c in ("id", "n", *_CARRIED)})


def _star_pairs(buckets: DataFrame) -> DataFrame:
    """Each member with its buckets' least ids, and in one bucket of each chunk with the other centre."""
    buckets = _known(buckets)
    centres = buckets.where("centre IS NOT NULL")
    near = (F.col("l.key") == F.col("r.key")) & (F.col("l.id") != F.col("r.id")) & _near("l", "r")
    pairs = buckets.alias("l").join(centres.alias("r"), near)
    return pairs.select(F.least("l.id", "r.id").alias("a"), F.greatest("l.id", "r.id").alias("b")).distinct()


def _cross_pairs(buckets: DataFrame, labels: DataFrame, label_rows: int) -> DataFrame:
    """All pairs of different components within the distances that share a bucket.

    Each has a member outside the component of the bucket's first centre: that member is on the left.
    """
    few = _bounded(labels, label_rows)
    own = few.select(F.col("node").alias("id"), F.col("label").alias("own"))
    first = few.select(F.col("node").alias("c0"), F.col("label").alias("first"))
    named = _known(buckets).join(own, "id", "left").join(first, "c0", "left")
    named = named.withColumns({"own": F.coalesce("own", "id"), "first": F.coalesce("first", "c0")}).drop("slot", "centre", "c0")
    outside = named.where("own <> first")
    met = (F.col("l.key") == F.col("r.key")) & ((F.col("r.own") == F.col("r.first")) | (F.col("l.own") < F.col("r.own"))) & _near("l", "r")
    pairs = outside.alias("l").join(named.alias("r"), met)
    return pairs.select(F.least("l.id", "r.id").alias("a"), F.greatest("l.id", "r.id").alias("b")).distinct()


def _label_rows(signed: DataFrame, named: DataFrame) -> DataFrame:
    """Every row with its component; a hot class is split by AQE, as the classes' side has one row of it."""
    alone = F.col("n") == 0
    rows = signed.withColumn("d0", F.when(alone, F.xxhash64("doc_id")).otherwise(F.col("d0")))
    met = rows.join(named, ["d0", "d1", "n"], "left")
    component = F.when(alone, F.col("doc_id")).otherwise(F.col("component"))
    return met.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"))


def op5_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read_table(spark, sf_dir, "documents"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: of each component the document with the least id goes on."""
    found = near_duplicates(docs)
    return drop_rows(docs, found.where(~F.col("kept")).select("doc_id"))


ORACLE = r"""
WITH RECURSIVE t AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w
  FROM documents
), sh AS (
  SELECT DISTINCT doc_id, array_to_string(w[s : s + least(len(w), 5) - 1], ' ') AS g
  FROM (SELECT doc_id, w, unnest(range(1, len(w) - least(len(w), 5) + 2)) AS s FROM t WHERE len(w) > 0)
), sizes AS (
  SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id
), shared AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM sh a JOIN sh b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL
), links AS (
  SELECT a, b FROM shared JOIN sizes x ON a = x.doc_id JOIN sizes y ON b = y.doc_id WHERE 100 * k >= 75 * (x.n + y.n - k)
), both_ways AS (
  SELECT a, b FROM links UNION SELECT b, a FROM links
), reach AS (
  SELECT doc_id AS a, doc_id AS b FROM t
  UNION
  SELECT reach.a, both_ways.b FROM reach JOIN both_ways ON reach.b = both_ways.a
), least_id AS (
  SELECT a AS doc_id, min(b) AS component_id FROM reach GROUP BY a
)
SELECT t.doc_id, coalesce(n, 0)::BIGINT AS n_shingles, component_id, t.doc_id = component_id AS kept
FROM t LEFT JOIN sizes USING (doc_id) JOIN least_id USING (doc_id)
"""
