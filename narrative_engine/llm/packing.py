"""Best-fit packing of documents into fixed-length sequences by bin completion.

Lengths are whole numbers up to the capacity, so the documents are first reduced to a histogram
of at most ``capacity`` rows and the packing is solved on that: around the largest length still
open, fillings are searched by branch and bound (largest first, a filling that swaps an item for
smaller ones is dominated and never tried before it; a branch ends where even a full fit could
not beat the incumbent's waste), with the best-fit filling as first incumbent.  A filling is used
as often as its lengths allow, so the work doesn't grow with the number of documents.  The better
of that and a whole best-fit-decreasing packing is the incumbent; where it needs more sequences
than the lower bound, undominated fillings are searched across sequences, with backtracking: first
as often as they go, for numbers near the bound, then in every multiplicity for each number from
the bound on, within about ``STEPS`` steps in all.  Pieces then
find their sequence from their rank among pieces of equal length, which is counted in salted
groups: no group of equal lengths meets in one task.

Defined results: null and empty texts are one piece of the end id alone; repeated rows are packed
as documents of their own; an empty table packs into nothing.
"""

from __future__ import annotations

import itertools
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from narrative_engine.llm.common import staged, table
from narrative_engine.llm.tokens import as_ids, encoder, vocabulary_path
from narrative_engine.shipping import ship

CAPACITY = 4096
END = 1
#: Rows of a salted group, about; groups of a block; and branches tried for one filling beyond the incumbent.
GROUP_ROWS = 2_000
BLOCK_GROUPS = 1_000
BRANCHES = 64
#: Steps of the search across sequences, a few seconds; if they don't run out, its result is the optimum.
STEPS = 2_000_000

PIECE = "doc_id long, piece int, start long, length long, ids_crc32 long"


def pieces(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """One row per piece; only documents beyond ``capacity`` are cut."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(path or vocabulary_path())
        for batch in batches:
            out: list[tuple] = []
            for doc_id, own_ids in zip(batch.column(0).to_pylist(), own.encode(batch.column(1))):
                ids = as_ids(own_ids, end)
                for k, at in enumerate(range(0, len(ids), capacity)):
                    part = ids[at : at + capacity]
                    out.append((doc_id, k, at, len(part), zlib.crc32(part.tobytes())))
            if out:
                cols = list(zip(*out))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), *[pa.array(c, pa.int64()) for c in cols[2:]]],
                    names=["doc_id", "piece", "start", "length", "ids_crc32"],
                )

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(cut, PIECE)


@dataclass(frozen=True)
class Filling:
    """``times`` sequences, each of these (length, count) in order."""

    times: int
    parts: tuple[tuple[int, int], ...]


def complete(room: int, have: np.ndarray, branches: int = BRANCHES) -> list[int]:
    """Lengths that fill ``room`` best, from the counts in ``have``."""
    best: list[int] = []
    lost = room

    def greedy(left: int, taken: dict[int, int]) -> list[int]:
        got = []
        while left > 0:
            open_ = np.flatnonzero(have[: left + 1])[::-1]
            x = next((int(x) for x in open_ if have[x] > taken.get(int(x), 0)), 0)
            if not x:
                break
            got.append(x)
            taken[x] = taken.get(x, 0) + 1
            left -= x
        return got

    best = greedy(room, {})
    lost = room - sum(best)
    tried = 0
    size = np.arange(room + 1) * np.minimum(have[: room + 1], room)
    most_of = np.cumsum(size)  # what all lengths up to one could fill

    def search(left: int, most: int, chosen: list[int]) -> None:
        nonlocal best, lost, tried
        if left < lost:
            best, lost = list(chosen), left
        if lost == 0 or tried >= branches or left == 0:
            return
        top = min(most, left)
        if left - int(most_of[top]) >= lost:
            return  # even all that is open leaves as much waste as the incumbent
        # two lengths that close the gap exactly
        one = np.arange(1, top + 1)
        rest = left - one
        fits = (have[one] > 0) & (rest <= one) & (rest > 0)
        fits[fits] &= have[rest[fits]] > 0
        for x in one[fits][::-1]:
            pick = [*chosen, int(x), int(left - x)]
            if all(have[v] >= pick.count(v) for v in {int(x), int(left - x)}):
                best, lost = pick, 0
                return
        for x in np.flatnonzero(have[: top + 1])[::-1]:
            x = int(x)
            if have[x] <= chosen.count(x):
                continue
            tried += 1
            search(left - x, x, [*chosen, x])
            if lost == 0 or tried >= branches:
                return

    if lost:
        search(room, room, [])
    return best


def completed(counts: np.ndarray, capacity: int) -> list[Filling]:
    """Fillings that use up ``counts``, each the best for the largest length then open."""
    have = np.zeros(capacity + 1, dtype=np.int64)
    have[: len(counts)] = counts
    out: list[Filling] = []
    for largest in range(capacity, 0, -1):
        while have[largest]:
            have[largest] -= 1
            chosen = complete(capacity - largest, have) if largest < capacity else []
            have[largest] += 1
            need: dict[int, int] = {largest: 1}
            for x in chosen:
                need[x] = need.get(x, 0) + 1
            times = int(min(have[x] // n for x, n in need.items()))
            for x, n in need.items():
                have[x] -= times * n
            out.append(Filling(times, tuple(sorted(need.items(), reverse=True))))
    return out


def best_fit(counts: np.ndarray, capacity: int) -> list[Filling]:
    """Best-fit decreasing on the histogram: each length goes where the least room is left."""
    room: dict[int, list[tuple[tuple[tuple[int, int], ...], int]]] = {}
    for x in np.flatnonzero(counts)[::-1].tolist():
        n = int(counts[x])
        while n:
            free = min((f for f in room if f >= x), default=capacity)
            parts, times = room[free].pop() if free in room else ((), n)
            if free in room and not room[free]:
                del room[free]
            most = free // x
            full, rest = min(times, n // most), n % most if n // most < times else 0
            if full:
                room.setdefault(free - most * x, []).append(((*parts, (x, most)), full))
            if rest:
                room.setdefault(free - rest * x, []).append(((*parts, (x, rest)), 1))
            if parts and times > full + bool(rest):
                room.setdefault(free, []).append((parts, times - full - bool(rest)))
            n -= full * most + rest
    return [Filling(times, parts) for groups in room.values() for parts, times in groups]


def fillings(lengths: list[int], have: np.ndarray, slack: int, capacity: int, steps: list[int]) -> Iterator[tuple[int, tuple[tuple[int, int], ...]]]:
    """(room left, parts) of the undominated fillings around the largest open length, largest parts first.

    One that leaves more than ``slack``, or room for an open length, is dominated.
    """
    start = next(j for j, x in enumerate(lengths) if have[x])

    def go(at: int, left: int, parts: tuple[tuple[int, int], ...]) -> Iterator[tuple[int, tuple[tuple[int, int], ...]]]:
        for j in range(at, len(lengths)):
            steps[0] -= 1
            if steps[0] < 0:
                return
            x = lengths[j]
            for n in range(min(int(have[x]), left // x), 0, -1):
                yield from go(j + 1, left - n * x, (*parts, (x, n)))
                if steps[0] < 0:
                    return
            if j == start:
                return
        used = dict(parts)
        if left <= slack and all(x > left or have[x] <= used.get(x, 0) for x in lengths[::-1]):
            yield left, parts

    yield from go(start, capacity, ())


def searched(counts: np.ndarray, sequences: int, capacity: int, steps: list[int], every: bool) -> list[Filling] | None:
    """A packing into ``sequences``, or None if ``steps`` end or there is none.

    Without ``every``, a filling is only tried as often as its lengths and the slack allow, so None proves nothing.
    """
    have = counts.copy()
    lengths = np.flatnonzero(have)[::-1].tolist()
    slack = sequences * capacity - int((np.arange(len(have)) * have).sum())

    def choices(slack: int, last: tuple) -> Iterator[tuple[int, int, tuple]]:
        largest = next(x for x in lengths if have[x])
        found = fillings(lengths, have, slack, capacity, steps)
        while some := sorted(itertools.islice(found, 256), key=lambda f: f[0]):
            for left, parts in some:
                if every and last and last[0][0] == largest and parts >= last:
                    continue  # the same sequences in another order
                most = min(int(have[x]) // n for x, n in parts)
                most = min(most, slack // left) if left else most
                for times in range(most, 0 if every else most - 1, -1):
                    yield times, left, parts

    chosen: list[tuple[int, int, tuple]] = []
    open_ = [choices(slack, ())]
    while steps[0] >= 0:
        steps[0] -= 1
        pick = next(open_[-1], None)
        if pick is None:
            open_.pop()
            if not open_:
                return None
            times, left, parts = chosen.pop()
            for x, n in parts:
                have[x] += times * n
            slack += times * left
            continue
        times, left, parts = pick
        chosen.append(pick)
        for x, n in parts:
            have[x] -= times * n
        slack -= times * left
        if not have.any():
            return [Filling(t, p) for t, _, p in chosen]
        open_.append(choices(slack, parts))
    return None


def pack(counts: np.ndarray, capacity: int = CAPACITY, steps: int = STEPS) -> list[Filling]:
    """Fillings that use up ``counts`` (by length)."""
    size = lambda found: sum(f.times for f in found)
    have = np.zeros(capacity + 1, dtype=np.int64)
    have[: len(counts)] = counts
    best = min((completed(have, capacity), best_fit(have, capacity)), key=size)
    length = np.arange(capacity + 1)
    bound = max(-(-int((length * have).sum()) // capacity), int(have[2 * length > capacity].sum()))
    near = [bound, *(bound + (1 << k) for k in range(size(best).bit_length()))]
    for sequences in near:
        if sequences < size(best) and (found := searched(have, sequences, capacity, [steps // 16], False)):
            best = found
    left = [steps // 2]
    for sequences in range(bound, size(best)):
        if found := searched(have, sequences, capacity, left, True):
            return found
        if left[0] < 0:
            break
    return best


def places(fillings: list[Filling], capacity: int = CAPACITY) -> np.ndarray:
    """Rows (length, first rank, first sequence, count a sequence, first offset), sorted; a few per filling."""
    used = np.zeros(capacity + 1, dtype=np.int64)
    rows, sequence = [], 0
    for f in fillings:
        offset = 0
        for length, n in f.parts:
            rows.append((length, used[length], sequence, n, offset))
            used[length] += f.times * n
            offset += length * n
        sequence += f.times
    rows.sort()
    return np.array(rows, dtype=np.int64).reshape(-1, 5)


def ranked(cut: DataFrame) -> DataFrame:
    """``cut`` with the rank (from 0) of each piece among those of its length."""
    total = cut.count()
    salt = F.pmod(F.xxhash64("doc_id", "piece"), F.lit(max(1, total // GROUP_ROWS)))
    rows = cut.withColumn("salt", salt)
    # running sums in two steps: over the groups of a block, and over the blocks of a length
    sums = rows.groupBy("length", "salt").agg(F.count("*").alias("n")).withColumn("block", F.floor(F.col("salt") / BLOCK_GROUPS))
    sums = sums.withColumn("inner", F.sum("n").over(Window.partitionBy("length", "block").orderBy("salt")) - F.col("n"))
    blocks = sums.groupBy("length", "block").agg(F.sum("n").alias("m"))
    blocks = blocks.select(F.col("length").alias("_bl"), F.col("block").alias("_b"), (F.sum("m").over(Window.partitionBy("length").orderBy("block")) - F.col("m")).alias("outer"))
    before = sums.join(blocks, (F.col("length") == F.col("_bl")) & (F.col("block") == F.col("_b"))).select(
        F.col("length").alias("_l"), F.col("salt").alias("_s"), (F.col("inner") + F.col("outer")).alias("base")
    )
    order = Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "start", "ids_crc32")
    numbered = rows.withColumn("own", F.row_number().over(order) - 1)
    return (
        numbered.join(staged(before), (F.col("length") == F.col("_l")) & (F.col("salt") == F.col("_s")))
        .select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("base") + F.col("own")).alias("rank"))
    )


def packed(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """Every piece with its sequence and offset."""
    spark = docs.sparkSession
    ship(spark)
    cut = staged(pieces(docs, path, capacity, end))
    counts = np.zeros(capacity + 1, dtype=np.int64)
    for length, n in cut.groupBy("length").agg(F.count("*")).collect():  # at most `capacity` rows
        counts[length] = n
    found = places(pack(counts, capacity), capacity)
    sent = spark.sparkContext.broadcast(found)

    def placed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = sent.value
        width = np.int64(1) << 40
        keys = rows[:, 0] * width + rows[:, 1]
        for b in batches:
            length, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
            row = rows[np.searchsorted(keys, length * width + rank, side="right") - 1]
            nth = rank - row[:, 1]
            sequence, offset = row[:, 2] + nth // row[:, 3], row[:, 4] + nth % row[:, 3] * length
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(sequence), pa.array(offset)], names=[*b.schema.names[:5], "sequence_id", "offset"])

    return ranked(cut).mapInArrow(placed, f"{PIECE}, sequence_id long, offset long")


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed(table(spark, sf_dir, "documents"))


ORACLE = None
