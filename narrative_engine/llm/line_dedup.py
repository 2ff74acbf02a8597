"""Line dedup by pairwise alignment with the earliest document that holds a shared anchor.

An anchor is a shortest run of lines with ``BLOCK_WORDS`` words or more, from its first line on or
back from its last; blank lines don't count.  Shorter runs, however frequent, make no pair.  Each
anchor points to its first document (the smallest doc_id) and its place there, found by a
pre-aggregated minimum, so a passage in a third of all documents gives each of them one partner
and never a group of pairs.  Nothing is lost by that: the anchors inside a run of enough words
that any earlier document holds cover the run, and the first owner of each holds all of it.  A
document is then aligned with each partner by patience: lines unique on both sides, in order,
first, then the stretches between them.  Aligned common blocks of ``BLOCK_WORDS`` words or more are
deleted from the later document; what was moved out of order is aligned again, and a block that
an alignment broke up is taken whole.

Defined results: a null text stays null; a text whose lines all go becomes empty; rows that share a
doc_id are never compared with each other, and equal rows get equal results; all columns of the
input are kept; an empty table stays empty.
"""

from __future__ import annotations

import bisect
import itertools
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from narrative_engine.llm.bytewords import hashed
from narrative_engine.llm.common import BLANK_RUN, BLANKS, let, staged, table
from narrative_engine.llm.shingles import _POWERS, mix
from narrative_engine.shipping import ship

BLOCK_WORDS = 20
BROADCAST_ROWS, BROADCAST_LINES = 300_000, 3_000_000


def own_lines(text: Column) -> Column:
    """Structs (at, h, n) of the lines with a word: place, hash of the trimmed line, words."""
    trimmed = F.transform(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x, i: F.struct(i.alias("at"), F.btrim(x, F.lit(BLANKS)).alias("line")))
    full = F.filter(trimmed, lambda x: x["line"] != "")
    return F.transform(full, lambda x: F.struct(x["at"].alias("at"), F.xxhash64(x["line"]).alias("h"), F.size(F.split(x["line"], BLANK_RUN)).alias("n")))


def windows(h: np.ndarray, n: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, first line and number of lines of the shortest runs of ``least`` words, forth from and back to every line."""
    ends = np.concatenate(([0], np.cumsum(n)))
    forth = np.searchsorted(ends, ends[:-1] + least)  # past the last line
    back = np.searchsorted(ends, ends[1:] - least, side="right") - 1
    i = np.concatenate((np.flatnonzero(forth <= len(n)), back[back >= 0]))
    e = np.concatenate((forth[forth <= len(n)], 1 + np.flatnonzero(back >= 0)))
    i, e = np.unique(np.stack((i, e)), axis=1)
    _POWERS.upto(len(h) + 1)
    total = np.zeros(len(h) + 1, dtype=np.uint64)
    np.cumsum(mix(h) * _POWERS.up[: len(h)], out=total[1:])
    return hashed(total, i, e), i, e - i


def anchors(lined: DataFrame, block_words: int) -> DataFrame:
    """(doc_id, text_key, h, i, k): the anchors of each document, ``k`` lines from line ``i`` on."""

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            h, n, ends = b.column(2).flatten(), b.column(3).flatten(), b.column(2).offsets.to_numpy()
            h, n, ends = h.to_numpy().view(np.uint64), n.to_numpy().astype(np.int64), ends - ends[0]
            for at in range(0, len(b), 1024):
                found = [windows(h[x:y], n[x:y], block_words) for x, y in itertools.pairwise(ends[at : at + 1025])]
                rows = np.repeat(np.arange(at, at + len(found)), [len(f[0]) for f in found])
                code, i, k = (np.concatenate(c) for c in zip(*found))
                yield pa.RecordBatch.from_arrays(
                    [b.column(0).take(pa.array(rows)), b.column(1).take(pa.array(rows)), pa.array(code.view(np.int64)), pa.array(i, pa.int32()), pa.array(k, pa.int32())],
                    names=["doc_id", "text_key", "h", "i", "k"],
                )

    return lined.select("doc_id", "text_key", "lines.h", "lines.n").mapInArrow(build, "doc_id long, text_key long, h long, i int, k int")


def rising(points: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The longest run of ``points`` (sorted by the first) whose second rises."""
    tails: list[int] = []
    where: list[int] = []
    back = [-1] * len(points)
    for k, (_, y) in enumerate(points):
        at = bisect.bisect_left(tails, y)
        if at == len(tails):
            tails.append(y)
            where.append(k)
        else:
            tails[at], where[at] = y, k
        back[k] = where[at - 1] if at else -1
    out, k = [], where[-1] if where else -1
    while k >= 0:
        out.append(points[k])
        k = back[k]
    return out[::-1]


def patience(points: set[tuple[int, int]]) -> list[tuple[int, int]]:
    """An alignment of (place, place there) matches: unique ones first, then what lies between."""
    todo, out = [sorted(points)], []
    while todo:
        inside = todo.pop()
        if not inside:
            continue
        xs, ys = Counter(x for x, _ in inside), Counter(y for _, y in inside)
        line = rising([p for p in inside if xs[p[0]] == ys[p[1]] == 1]) or rising(sorted(inside, key=lambda p: (p[0], -p[1])))
        out += line
        edges = [(-1, -1), *line, (1 << 60, 1 << 60)]
        if len(line) < len(inside):
            lefts = [e[0] for e in edges]
            between: dict[int, list] = defaultdict(list)
            for p in inside:
                k = bisect.bisect_left(lefts, p[0]) - 1
                if edges[k][0] < p[0] < edges[k + 1][0] and edges[k][1] < p[1] < edges[k + 1][1]:
                    between[k].append(p)
            todo += between.values()
    return sorted(out)


def common_blocks(points: set[tuple[int, int]], words: list[int], least: int) -> list[int]:
    """Places that lie in common blocks of at least ``least`` words, aligned or broken up by the alignment."""
    gone: list[int] = []
    everywhere = sorted(points, key=lambda p: (p[1] - p[0], p[0]))
    while points:
        aligned, found, k = patience(points), [], 0
        while k < len(aligned):
            e = k + 1
            while e < len(aligned) and aligned[e][0] == aligned[e - 1][0] + 1 and aligned[e][1] == aligned[e - 1][1] + 1:
                e += 1
            places = [x for x, _ in aligned[k:e]]
            if sum(words[x] for x in places) >= least:
                found += places
            k = e
        gone += found
        drop = set(found)
        points = {p for p in points if p[0] not in drop} - set(aligned)
    k = 0
    while k < len(everywhere):
        e = k + 1
        while e < len(everywhere) and everywhere[e] == (everywhere[e - 1][0] + 1, everywhere[e - 1][1] + 1):
            e += 1
        places = [x for x, _ in everywhere[k:e]]
        if sum(words[x] for x in places) >= least:
            gone += places
        k = e
    return sorted(set(gone))


def removals(docs: DataFrame, block_words: int = BLOCK_WORDS) -> DataFrame:
    """(doc_id, text_key, gone, partners, n_gone_words): places of the lines to delete, for documents that have any."""
    ship(docs.sparkSession)
    lined = staged(docs.where("doc_id IS NOT NULL").select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("text_key"), own_lines(F.col("text")).alias("lines")))
    asked = staged(anchors(lined, block_words))
    first = staged(
        asked.groupBy("h").agg(F.min(F.struct("doc_id", "i")).alias("first"), F.max("doc_id").alias("last"))
        .where("first.doc_id < last").select("h", F.col("first.doc_id").alias("ref"), F.col("first.i").alias("there"))
    )
    met = asked.join(first, "h").where("doc_id > ref").groupBy("doc_id", "text_key").agg(F.collect_set(F.struct("ref", "i", "there", "k")).alias("met"))
    rows = met.join(lined.dropDuplicates(["doc_id", "text_key"]), ["doc_id", "text_key"])
    rows = rows.select("doc_id", "text_key", "met", F.col("lines.at").alias("at"), F.col("lines.n").alias("n"))

    def align(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for doc_id, key, met, at, n in zip(*[c.to_pylist() for c in b.columns]):
                by: dict[int, set] = defaultdict(set)
                for m in met:
                    for k in range(m["k"]):
                        by[m["ref"]].add((m["i"] + k, m["there"] + k))
                gone: set[int] = set()
                partners = []
                for ref in sorted(by):
                    if found := common_blocks(by[ref], n, block_words):
                        gone.update(found)
                        partners.append(ref)
                if gone:
                    out.append((doc_id, key, [at[i] for i in sorted(gone)], partners, sum(n[i] for i in gone)))
            if out:
                cols = list(zip(*out))
                kinds = [pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.int64()), pa.int64()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=["doc_id", "text_key", "gone", "partners", "n_gone_words"])

    return rows.mapInArrow(align, "doc_id long, text_key long, gone array<int>, partners array<long>, n_gone_words long")


def deduped(docs: DataFrame, block_words: int = BLOCK_WORDS) -> DataFrame:
    """``docs`` with the common blocks gone, and a struct ``_dedup``: lines, removed lines and words, partners."""
    found = staged(removals(docs, block_words))
    rows, lines = found.agg(F.count("*"), F.coalesce(F.sum(F.size("gone")), F.lit(0))).first()
    cut = found.select(F.col("doc_id").alias("_id"), F.col("text_key").alias("_key"), "gone", "partners", "n_gone_words")
    cut = F.broadcast(cut) if rows <= BROADCAST_ROWS and lines <= BROADCAST_LINES else cut
    held = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_doc"))
    text = F.col("_doc.text")
    joined = held.join(cut, (F.col("_doc.doc_id").cast("long") == F.col("_id")) & (F.xxhash64(text) == F.col("_key")), "left")
    kept = lambda ls: F.array_join(F.transform(F.array_except(F.sequence(F.lit(0), F.size(ls) - 1), F.col("gone")), lambda i: F.get(ls, i)), "\n")
    new = F.when(F.col("gone").isNull(), text).otherwise(let(F.split(text, "\n"), kept))
    told = F.struct(
        F.size(F.split(F.coalesce(text, F.lit("")), "\n")).cast("long").alias("n_lines"),
        F.when(F.col("gone").isNull(), 0).otherwise(F.size("gone")).cast("long").alias("n_removed"),
        F.coalesce("n_gone_words", F.lit(0)).alias("n_removed_words"),
        F.coalesce("partners", F.array().cast("array<bigint>")).alias("partners"),
    )
    return joined.select(*[new.alias(c) if c == "text" else F.col("_doc")[c].alias(c) for c in docs.columns], told.alias("_dedup"))


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduped(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "text", "_dedup.*")


ORACLE = None
