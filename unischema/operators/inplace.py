"""Pairs that meet at a common value, and balls of many starts, made in place: no pair is exchanged.

Names are numbered, the rows that meet are arrays of numbers in every task, and each task makes all pairs of
its range of first names, or all rows of its starts.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Rows up to which the arrays are sent to every task; callers exchange their pairs beyond.
ROWS = 30_000_000
#: Meetings of one step, and of one task about.
STEP, TASK = 2_000_000, 16_000_000
#: Pairs of one batch of the result.
BATCH = 100_000
#: Cells of the table of lengths, starts by names, that a task fills at a time.
CELLS = 2_000_000


def pairs_in_place(spark: SparkSession, names: pa.Array, ids: np.ndarray, starts: np.ndarray, ends: np.ndarray, values: np.ndarray, schema: str, more: Callable | None = None) -> DataFrame:
    """Distinct pairs of ``names``: row ``i`` lets ``ids[i]`` meet all larger numbers in ``values[starts[i]:ends[i]]``.

    ``schema`` names both columns and those of ``more(first, second, n)``: arrays for the numbers of pairs
    that met ``n`` times. Numbers follow the order of names, so the first name of a pair is the least.
    """
    size = len(names)
    work = np.bincount(ids, weights=ends - starts, minlength=size).cumsum() if len(ids) else np.zeros(1)
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), int(work[-1] // TASK) + 1)
    inner = np.searchsorted(work, np.linspace(0, work[-1], tasks + 1)[1:-1]) + 1
    bounds = np.unique(np.clip(np.concatenate([[0], inner, [size]]), 0, size))
    data = spark.sparkContext.broadcast((names, ids, starts, ends, values, bounds))
    step, batch = STEP, BATCH

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, ids, starts, ends, values, bounds = data.value
        size = len(names)

        def gathered(begin: np.ndarray, length: np.ndarray) -> np.ndarray:
            last = np.cumsum(length)
            return values[np.arange(last[-1]) + np.repeat(begin - last + length, length)]

        def counted(low: int, high: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
            """First and second numbers and how often they met, for all first ones from ``low`` to ``high``."""
            rows = np.flatnonzero((ids >= low) & (ids < high) & (ends > starts))
            rows = rows[np.argsort(ids[rows], kind="stable")]
            own, begin = ids[rows].astype("int64"), starts[rows].astype("int64")
            length = ends[rows].astype("int64") - begin
            done = np.cumsum(length)
            until = lambda place: int(np.searchsorted(done, (done[place - 1] if place else 0) + step, "right"))
            place = 0
            while place < len(rows):
                stop = until(place)
                if stop < len(rows):
                    stop = int(np.searchsorted(own, own[stop]))
                if stop > place:
                    key = np.repeat(own[place:stop], length[place:stop]) * size + gathered(begin[place:stop], length[place:stop])
                    key.sort()
                    edge = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
                    n = np.diff(np.append(edge, len(key)))
                    first, second = np.divmod(key[edge], size)
                else:
                    # one name alone has more meetings than a step: they are counted in parts
                    stop, n = int(np.searchsorted(own, own[place], "right")), np.zeros(size, "int64")
                    at = place
                    while at < stop:
                        to = min(max(until(at), at + 1), stop)
                        n += np.bincount(gathered(begin[at:to], length[at:to]), minlength=size)
                        at = to
                    second = np.flatnonzero(n)
                    first, n = np.full(len(second), own[place]), n[second]
                kept = second > first
                yield first[kept], second[kept], n[kept]
                place = stop

        for numbers in batches:
            for block in numbers.column(0).to_pylist():
                for first, second, n in counted(bounds[block], bounds[block + 1]):
                    for at in range(0, len(first), batch):
                        x, y, times = first[at : at + batch], second[at : at + batch], n[at : at + batch]
                        columns = [names.take(pa.array(x)), names.take(pa.array(y)), *(more(x, y, times) if more else [])]
                        yield pa.RecordBatch.from_arrays(columns, [f"c{i}" for i in range(len(columns))])

    columns = ", ".join(f"c{i} {part.split()[1]}" for i, part in enumerate(schema.split(", ")))
    blocks = len(bounds) - 1
    found = spark.range(0, blocks, 1, max(blocks, 1)).mapInArrow(meet, columns)
    return found.toDF(*[part.split()[0] for part in schema.split(", ")])


def balls_in_place(spark: SparkSession, names: pa.Array, starts: np.ndarray, begin: np.ndarray, to: np.ndarray, steps: list[str], tasks: int) -> DataFrame:
    """``start, end, len`` with the least length of what ``steps`` reach from numbered ``starts``, themselves at 0.

    ``to[begin[i]:begin[i + 1]]`` are the neighbours of ``i``. In a step ``new`` only what the one before reached
    first meets its neighbours; a step ``all`` is the min-plus product of all rows with the ball of one hop.
    """
    data = spark.sparkContext.broadcast((names, starts, begin, to))
    cells, step, batch = CELLS, STEP, BATCH

    def reach(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, starts, begin, to = data.value
        size, degree, beyond = len(names), np.diff(begin), len(steps) + 1
        kind = np.uint8 if beyond < 256 else np.int32

        def onward(rows: np.ndarray, length: int, out: np.ndarray) -> None:
            """Neighbours of the cells ``rows`` are at ``length`` in ``out``, if they are not nearer."""
            node = rows % size
            n = degree[node]
            done = np.cumsum(n)
            place = 0
            while place < len(rows):
                stop = max(int(np.searchsorted(done, (done[place - 1] if place else 0) + step, "right")), place + 1)
                some, last = n[place:stop], done[place:stop] - (done[place - 1] if place else 0)
                cell = np.repeat(begin[node[place:stop]] - last + some, some)
                cell += np.arange(last[-1])
                cell = to[cell] + np.repeat(rows[place:stop] - node[place:stop], some)
                out[cell[out[cell] > length]] = length
                place = stop

        def table(own: np.ndarray) -> np.ndarray:
            lengths = np.full(len(own) * size, beyond, kind)
            lengths[np.arange(len(own)) * size + own] = 0
            for number, how in enumerate(steps):
                out = lengths if how == "new" else lengths.copy()
                for length in [number] if how == "new" else range(number + 1):
                    onward(np.flatnonzero(lengths == length), length + 1, out)
                lengths = out
            return lengths

        at_once = max(1, cells // max(size, 1))
        for numbers in batches:
            for task in numbers.column(0).to_pylist():
                mine = starts[task::tasks]
                for low in range(0, len(mine), at_once):
                    own = mine[low : low + at_once]
                    lengths = table(own)
                    found = np.flatnonzero(lengths < beyond)
                    for at in range(0, len(found), batch):
                        some = found[at : at + batch]
                        x, y = np.divmod(some, size)
                        yield pa.RecordBatch.from_arrays([names.take(pa.array(own[x])), names.take(pa.array(y)), pa.array(lengths[some].astype("int32"))], ["c0", "c1", "c2"])

    return spark.range(0, tasks, 1, tasks).mapInArrow(reach, "c0 string, c1 string, c2 int").toDF("start", "end", "len")
