"""Language identification by n-gram filters that answer for all languages at once.

A bit-sliced Bloom filter has one word of bits per position, one bit per language.  The AND of the
words at a gram's positions gives every language that holds the gram.  Per language the answers of
a text are counted, the counts are corrected by that filter's false-positive rate, and the largest
corrected count decides.

Grams are 4 bytes of the text with ASCII letters lowered and other ASCII characters taken as one
blank.  A language holds a gram that it uses at least ``SHARE`` times as often as the language that
uses it most.  Grams are counted on about ``SAMPLE`` documents of each language (by hash of doc_id;
a documented bound), at most ``GRAMS`` of a language are kept; every document is judged on its whole text.

Defined results: ``und`` with score 0 for null texts, texts without a letter, and when nothing was
learnt; null languages teach nothing; ties go to the first language by name; repeated rows are
judged alike; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from narrative_engine.llm.common import staged, table
from narrative_engine.llm.shingles import mix, text_bytes
from narrative_engine.llm.toxicity import HELD_OUT, fold
from narrative_engine.shipping import ship

SAMPLE = 3_000
GRAMS = 60_000
SHARE = 0.3
LEAST = 3  # occurrences
BITS, HASHES = 21, 2
UNKNOWN = "und"

_BLANK = np.uint8(32)
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[:128] = _BLANK
_FOLD[97:123] = np.arange(97, 123)
_FOLD[65:91] = np.arange(97, 123)


def grams(data: np.ndarray) -> np.ndarray:
    """Codes of the text's grams, blank runs taken as one."""
    x = _FOLD[data]
    keep = np.ones(len(x), dtype=bool)
    keep[1:] = (x[1:] != _BLANK) | (x[:-1] != _BLANK)
    x = np.concatenate(([_BLANK], x[keep], [_BLANK, _BLANK])).astype(np.uint32)
    code = x[:-3] << np.uint32(24) | x[1:-2] << np.uint32(16) | x[2:-1] << np.uint32(8) | x[3:]
    return code[(x[1:-2] != _BLANK) | (x[2:-1] != _BLANK)]


def has_letter(data: np.ndarray) -> bool:
    if ((data | np.uint8(32)) - np.uint8(97) < 26).any():
        return True
    return bool((data >= 128).any()) and any(c.isalpha() for c in data.tobytes().decode("utf-8", "replace"))


def positions(codes: np.ndarray) -> np.ndarray:
    """HASHES x grams places in the filter."""
    h = mix(codes.astype(np.uint64))
    mask = np.uint64((1 << BITS) - 1)
    return np.stack([(h >> np.uint64(BITS * k)) & mask for k in range(HASHES)]).astype(np.int64)


@dataclass(frozen=True)
class Filters:
    languages: tuple[str, ...]
    slices: np.ndarray  # 2^BITS x words of 64 bits
    false: np.ndarray  # rate of each language

    def counts(self, codes: np.ndarray) -> np.ndarray:
        """Grams of ``codes`` that each language holds."""
        at = positions(codes)
        found = self.slices[at[0]]
        for row in at[1:]:
            found = found & self.slices[row]
        return np.array([int((found[:, k >> 6] >> np.uint64(k & 63) & np.uint64(1)).sum()) for k in range(len(self.languages))], dtype=np.float64)

    def judge(self, data: np.ndarray) -> tuple[str, float]:
        if not self.languages or not has_letter(data):
            return UNKNOWN, 0.0
        codes = grams(data)
        true = np.clip((self.counts(codes) - len(codes) * self.false) / (1 - self.false), 0, None)
        k = int(true.argmax())
        return self.languages[k], float(min(1.0, true[k] / max(1, len(codes))))


def build(rows: list[tuple[str, np.ndarray]]) -> Filters:
    """Filters from the grams that each language holds."""
    names = tuple(n for n, _ in sorted(rows, key=lambda r: r[0]))
    slices = np.zeros((1 << BITS, max(1, -(-len(names) // 64))), dtype=np.uint64)
    held = dict(rows)
    for k, name in enumerate(names):
        for at in positions(held[name]):
            slices[at, k >> 6] |= np.uint64(1 << (k & 63))
    fill = [float((slices[:, k >> 6] >> np.uint64(k & 63) & np.uint64(1)).mean()) for k in range(len(names))]
    return Filters(names, slices, np.array(fill, dtype=np.float64) ** HASHES)


def train(docs: DataFrame) -> Filters:
    """Filters from the documents outside the held-out fold that have a language."""
    ship(docs.sparkSession)
    known = docs.where("lang IS NOT NULL AND text IS NOT NULL AND doc_id IS NOT NULL").where(fold() != HELD_OUT)
    sizes = known.groupBy("lang").count().collect()  # a row per language
    if not sizes:
        return build([])
    chance = F.create_map(*[F.lit(v) for r in sizes for v in (r["lang"], min(1.0, SAMPLE / r["count"]))])
    draw = F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < F.try_element_at(chance, F.col("lang")) * 1_000_000
    names = sorted(r["lang"] for r in sizes)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, ends = text_bytes(b.column(1))
            langs = np.array([names.index(x) for x in b.column(0).to_pylist()], dtype=np.int64)
            found = [grams(raw[i:j]) for i, j in zip(ends[:-1], ends[1:])]
            key = np.concatenate(found).astype(np.int64) if found else np.empty(0, dtype=np.int64)
            both, n = np.unique(np.repeat(langs, [len(f) for f in found]) << 32 | key, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(both >> 32), pa.array(both & 0xFFFFFFFF), pa.array(n)], names=["l", "gram", "n"])

    seen = staged(known.where(draw).select("lang", "text").mapInArrow(count, "l long, gram long, n long").groupBy("l", "gram").agg(F.sum("n").alias("n")))
    totals = F.broadcast(seen.groupBy("l").agg(F.sum("n").alias("total")))  # a row per language
    rated = seen.where(F.col("n") >= LEAST).join(totals, "l").withColumn("rate", F.col("n") / F.col("total"))
    most = rated.groupBy("gram").agg(F.max("rate").alias("most"))
    held = staged(rated.join(most, "gram").where(F.col("rate") >= SHARE * F.col("most")).select("l", "gram", "rate"))
    out = []
    order = F.row_number().over(Window.partitionBy("l").orderBy(F.desc("rate"), "gram"))
    for at in range(0, len(names), 64):  # a bounded list of grams for each language
        best = held.where(F.col("l").between(at, at + 63)).withColumn("r", order).where(F.col("r") <= GRAMS).select("l", "gram").toArrow()
        l, gram = (best.column(c).to_numpy() for c in ("l", "gram"))
        out += [(names[k], gram[l == k].astype(np.uint32)) for k in range(at, min(at + 64, len(names)))]
    return build(out)


def identified(docs: DataFrame, filters: Filters) -> DataFrame:
    ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(filters)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, ends = text_bytes(b.column(1))
            found = [sent.value.judge(raw[i:j]) for i, j in zip(ends[:-1], ends[1:])]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x for x, _ in found], pa.string()), pa.array([x for _, x in found], pa.float64())], names=["doc_id", "lang_pred", "score"])

    rows = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(judge, "doc_id long, lang_pred string, score double")
    return rows.select("doc_id", (fold() == HELD_OUT).alias("held_out"), "lang_pred", "score")


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return identified(docs, train(docs))


ORACLE = None
