"""Best-fit packing of token sequences with certified bounds and repacking of the gaps.

Documents are tokenised once, where they lie; only lengths move afterwards. Pieces are dealt into
partitions of bounded size, each packed by best-fit decreasing. A lower bound from dual feasible
functions certifies each partition: where bins and bound agree its packing is optimal. Partitions
with a gap give up their loosest bins, certified ones only bins with a quarter or more of their room
left; the documents of several partitions meet in one group, best-fit decreasing runs again, and the
new bins replace the old ones if they are fewer. Rounds go on until the loose bins of all partitions
have met, which takes a logarithm of their number; a partition gives at most what one group can take
from each of its ``FAN`` members, so that groups stay bounded.

Defined results: a null text is empty and gives the one token 0; a null id is carried along; rows
that repeat are packed each; columns beyond ``doc_id`` and ``text`` are ignored; an empty table
gives an empty result. Texts of any length are tokenised whole.
"""

from __future__ import annotations

import base64
import json
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unischema.llm.common import arrow_ready, cut, read_table

CAPACITY = 2048
END_ID = 0
#: Pieces that one packing task holds.
GROUP_PIECES = 8192
#: Partitions that exchange documents with each other in one round.
FAN = 8
#: A run of characters without white space beyond this goes to the reference tokenizer.
LONG_RUN = 2000


@lru_cache(maxsize=2)
def _whole(name: str):
    """The JSON tokenizer, loaded only where a text needs it."""
    import public_tokenizers
    from tokenizers import Tokenizer

    return Tokenizer.from_file(public_tokenizers.path(f"{name}.json"))


@lru_cache(maxsize=2)
def _encoder(name: str):
    """``encode(text)`` for a byte-level BPE named without its suffix.

    The rank file holds the same vocabulary as the JSON file and encodes several times faster;
    texts with a special token's string go to the JSON tokenizer.
    """
    import public_tokenizers
    import tiktoken

    with open(public_tokenizers.path(f"{name}.json"), encoding="utf-8") as file:
        special = [t["content"] for t in json.load(file)["added_tokens"]]
    with open(public_tokenizers.path(f"{name}.tiktoken"), "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    fast = tiktoken.Encoding(name, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    def encode(text: str) -> list[int]:
        odd = any(s in text for s in special) or (len(text) > LONG_RUN and max(map(len, text.split()), default=0) > LONG_RUN)
        return _whole(name).encode(text, add_special_tokens=False).ids if odd else fast.encode_ordinary(text)

    return encode


def token_ids(text: str | None, tokenizer: str = "byte_bpe_50k") -> np.ndarray:
    """The ids of one document, closed by ``END_ID``, as little-endian unsigned 32-bit."""
    return np.array([*_encoder(tokenizer)(text or ""), END_ID], dtype="<u4")


def cuts(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """``(start, length)`` of the pieces of ``n`` tokens; only the first may be shorter than full."""
    first = (n - 1) % capacity + 1
    return [(0, first), *((s, capacity) for s in range(first, n, capacity))]


PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def tokenise(docs: DataFrame, tokenizer: str = "byte_bpe_50k", capacity: int = CAPACITY) -> DataFrame:
    """One row per piece of each document."""
    arrow_ready(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple] = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = token_ids(text.as_py(), tokenizer)
                out += [(doc, i, s, n, zlib.crc32(ids[s : s + n].tobytes())) for i, (s, n) in enumerate(cuts(len(ids), capacity))]
            columns = list(zip(*out, strict=True)) if out else [()] * 5
            types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, PIECES)


def lower_bound(lengths: np.ndarray, capacity: int = CAPACITY, terms: int = 32) -> int:
    """Bins that any packing needs, by two families of dual feasible functions.

    For a threshold t up to half: pieces over ``capacity - t`` count whole, those under t not at
    all, others by size. For k: a size x counts ``floor((k+1)x/c)/k`` unless that is exact, then x/c.
    """
    if not len(lengths):
        return 0
    count = np.bincount(lengths, minlength=capacity + 1).astype(np.int64)
    size = np.arange(capacity + 1)
    tail = np.append(np.cumsum(count[::-1])[::-1], 0)
    mass = np.append(0, np.cumsum(count * size))
    best = 0
    t = np.arange(0, capacity // 2 + 1)
    whole = tail[capacity - t + 1]
    middle = mass[capacity - t + 1] - mass[t]
    best = int(np.max(whole - (-middle // capacity)))
    for k in range(1, terms + 1):
        scaled = (k + 1) * size
        exact = scaled % capacity == 0
        value = np.where(exact, size * k, (scaled // capacity) * capacity)  # in units of 1 / (k * capacity)
        best = max(best, int(-(-int((count * value).sum()) // (k * capacity))))
    return best


def best_fit(lengths: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best-fit decreasing: bin and offset of each piece, and the room left in each bin.

    ``open_`` has a bit for every amount of room that some bin has left, so the tightest bin that
    takes a piece is the lowest set bit at or above its length.
    """
    bins = np.zeros(len(lengths), np.int64)
    offsets = np.zeros(len(lengths), np.int64)
    rooms: list[int] = []
    by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    open_ = 0
    for i in np.argsort(-lengths, kind="stable").tolist():
        need = int(lengths[i])
        fits = open_ >> need
        if fits:
            room = need + (fits & -fits).bit_length() - 1
            at = by_room[room].pop()
            if not by_room[room]:
                open_ &= ~(1 << room)
        else:
            room, at = capacity, len(rooms)
            rooms.append(capacity)
        bins[i], offsets[i] = at, capacity - room
        left = room - need
        rooms[at] = left
        if left:
            by_room[left].append(at)
            open_ |= 1 << left
    return bins, offsets, np.array(rooms, np.int64)


PACKED = f"{PIECES}, sequence_id long, offset long, part long, gap int, loose boolean"


def _pack(capacity: int, level: int, quota: int):
    """A function for ``applyInPandas`` that packs or repacks one group of pieces."""

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        lengths = rows["length"].to_numpy(np.int64)
        bins, offsets, rooms = best_fit(lengths, capacity)
        before = rows["sequence_id"].nunique() if level else len(rows) + 1
        bound = lower_bound(lengths, capacity)
        if len(rooms) < before:
            rows = rows.assign(sequence_id=((level << 56) | (int(key[0]) << 24)) + bins, offset=offsets)
            used, left = bins, rooms
        else:
            used, seen = pd.factorize(rows["sequence_id"])
            left = capacity - np.bincount(used, weights=lengths, minlength=len(seen)).astype(np.int64)
        order = np.argsort(-left, kind="stable")
        order = order[left[order] > 0]
        gap = len(left) - bound
        order = order[(gap > 0) | (left[order] >= capacity // 4)]
        held = np.bincount(used, minlength=len(left))[order].cumsum()
        loose = np.zeros(len(left), bool)
        loose[order[held <= quota]] = True
        return rows.assign(part=int(key[0]), gap=gap, loose=loose[used])

    return run


def best_fit_packing(docs: DataFrame, capacity: int = CAPACITY, tokenizer: str = "byte_bpe_50k", group_pieces: int = GROUP_PIECES) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32, sequence_id, offset, gap`` for each piece.

    Packing is over bounded groups; ``gap`` is by how many sequences the group in which the piece was last
    packed is above its certified bound. ``pack_report`` gives the same for the whole.
    """
    pieces = cut(tokenise(docs, tokenizer, capacity))
    return pack_pieces(pieces, capacity, group_pieces).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", "gap")


def pack_pieces(pieces: DataFrame, capacity: int = CAPACITY, group_pieces: int = GROUP_PIECES) -> DataFrame:
    """Packs a materialised table of pieces; also returns each piece's partition and its gap.

    Rounds of repacking go on until no partition has loose bins, or all that are left have met in one group.
    """
    parts = max(1, -(-pieces.count() // group_pieces))
    dealt = pieces.select("*", *[F.lit(None).cast(t).alias(c) for c, t in (("sequence_id", "long"), ("offset", "long"))])
    dealt = dealt.withColumn("part", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(parts)))
    quota = group_pieces // FAN
    packed = dealt.groupBy("part").applyInPandas(_pack(capacity, 0, quota), PACKED)
    level = 0
    while parts > 1:
        level += 1
        packed = cut(packed)
        moves = F.col("loose")
        if packed.where(moves).isEmpty():
            break
        parts = -(-parts // FAN)
        group = F.pmod(F.col("part"), F.lit(parts))
        again = packed.where(moves).withColumn("part", group).groupBy("part").applyInPandas(_pack(capacity, level, quota), PACKED)
        packed = packed.where(~moves).withColumn("loose", F.lit(False)).unionByName(again)
    return packed


def pack_report(packed: DataFrame, capacity: int = CAPACITY) -> dict[str, int]:
    """Sequences used, and the bound that the lengths of all pieces certify (a histogram, at most ``capacity`` rows)."""
    histogram = packed.groupBy("length").count().collect()
    lengths = np.repeat([r["length"] for r in histogram], [r["count"] for r in histogram]).astype(np.int64)
    return {"sequences": packed.select("sequence_id").distinct().count(), "bound": lower_bound(lengths, capacity)}


def op10_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return best_fit_packing(read_table(spark, sf_dir, "documents"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage, the last: pieces with their places in sequences."""
    return best_fit_packing(docs)
