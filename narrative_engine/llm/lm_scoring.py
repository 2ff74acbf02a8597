"""Cross-entropy difference of two matched bigram models.

The target model is counted over the documents labelled good, the background model over all
others; both share one vocabulary, one smoothing and one set of bigrams, so their losses differ
only by the texts they saw.  Every word is in the vocabulary and every bigram that occurs ``LEAST``
times has counts of its own, so the models grow with the corpus and stay in tables; rarer bigrams
fall back to the unigrams.  Documents are read once into chunks of about ``CHUNK_BYTES``.  A chunk
deals the keys of its different words and bigrams into buckets, one row each; a bucket sums the
counts of all chunks and answers each with those of its keys.  The number of buckets grows with the
corpus, the commonest key has one entry a chunk, and no table is sent to the workers.  A document's
score is its mean per-token loss under the target model minus that under the background model: the
lower, the more it is like the target.

Defined results: null texts and texts without words have no tokens, losses of 0 and a score of 0;
without labels the target model is the uniform start of the smoothing; repeated rows count as
often as they occur; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from narrative_engine.llm.bytewords import word_hashes
from narrative_engine.llm.common import staged, table
from narrative_engine.llm.shingles import _ODD, mix, text_bytes
from narrative_engine.shipping import ship

LEAST = 2  # occurrences of a bigram that is counted on its own
WEIGHT = 32.0  # of the unigram model in a bigram's smoothing
BROADCAST_IDS = 2_000_000
CHUNK_BYTES = 8 << 20
BUCKET_KEYS = 1 << 21

DEALT = "bucket int, chunk long, asks boolean, keys binary, t binary, b binary"
ANSWER = "chunk long, bucket int, n_words long, places binary, t binary, b binary"
CHUNK = "chunk long, doc_ids array<long>, targets array<boolean>, counts array<long>, words binary, ids binary"
START = np.uint64(0x5851F42D4C957F2D)  # stands before a text's first word


@dataclass(frozen=True)
class Models:
    """Both models; pairs are (target, background).  Words have even keys, bigrams odd ones."""

    chunks: DataFrame  # of the texts that are counted
    words: int
    tokens: tuple[int, int]
    starts: tuple[int, int]


def squeezed(x: np.ndarray) -> bytes:
    """Small whole numbers as compressed byte planes."""
    return zstandard.compress(np.ascontiguousarray(x.astype("<i8").view(np.uint8).reshape(-1, 8).T).tobytes(), 1)


def unsqueezed(raw) -> np.ndarray:
    planes = np.frombuffer(zstandard.decompress(raw), np.uint8).reshape(8, -1)
    return np.ascontiguousarray(planes.T).reshape(-1).view("<i8")


def flagged(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``doc_id``, ``text`` and ``target``: whether the document is labelled good."""
    good = staged(labels.where("quality = 1").select(F.col("doc_id").alias("_id")).distinct())
    good = F.broadcast(good) if good.count() <= BROADCAST_IDS else good
    rows = docs.select("doc_id", "text").join(good, F.col("doc_id") == F.col("_id"), "left")
    return rows.select("doc_id", "text", F.col("_id").isNotNull().alias("target"))


def chunked(rows: DataFrame) -> DataFrame:
    """Runs of documents: their different words' hashes, sorted, and each token's place among them."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, n = TaskContext.get().partitionId(), 0
        held, doc_ids, targets, size = [], [], [], 0

        def close() -> pa.RecordBatch:
            nonlocal n, held, doc_ids, targets, size
            words, ids = np.unique(np.concatenate(held), return_inverse=True)
            row = [(part << 32) + n, doc_ids, targets, [len(h) for h in held], words.tobytes(), squeezed(ids)]
            kinds = [pa.int64(), pa.list_(pa.int64()), pa.list_(pa.bool_()), pa.list_(pa.int64()), pa.binary(), pa.binary()]
            n, held, doc_ids, targets, size = n + 1, [], [], [], 0
            return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, kinds)], names=[c.split()[0] for c in CHUNK.split(", ")])

        for b in batches:
            for at in range(0, len(b), 2048):
                some = b.slice(at, 2048)
                raw, ends = text_bytes(some.column(1))
                for doc_id, target, i, j in zip(some.column(0).to_pylist(), some.column(2).to_pylist(), ends[:-1], ends[1:]):
                    held.append(word_hashes(raw[i:j]))
                    doc_ids.append(doc_id)
                    targets.append(target)
                    size += j - i
                    if size >= CHUNK_BYTES:
                        yield close()
        if held:
            yield close()

    ship(rows.sparkSession)
    return staged(rows.select(F.col("doc_id").cast("long"), "text", "target").mapInArrow(read, CHUNK))


def bigrams(counts: np.ndarray, ids: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Different pairs (before * (width + 1) + word) of a chunk and each token's place among them; ``width`` starts a text."""
    before = np.concatenate(([width], ids[:-1])).astype(np.int64)
    first = np.cumsum(counts) - counts
    before[first[counts > 0]] = width
    return np.unique(before[: len(ids)] * (width + 1) + ids, return_inverse=True)


def unpacked(b: pa.RecordBatch, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Words, token places and documents' token numbers of chunk row ``k``."""
    words, ids = np.frombuffer(b.column("words")[k].as_buffer(), np.uint64), unsqueezed(b.column("ids")[k].as_buffer())
    return words, ids, b.column("counts")[k].values.to_numpy().astype(np.int64)


def keys_of(words: np.ndarray, codes: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Keys of a chunk's words and bigrams, their order by bucket and where each bucket starts in it."""
    hashes, width = np.concatenate((mix(words), [START])), len(words) + 1
    pairs = mix(hashes[codes // width] * _ODD + hashes[codes % width])
    keys = np.concatenate((hashes[:-1] & ~np.uint64(1), pairs | np.uint64(1)))
    bucket = ((keys >> np.uint64(20)) % np.uint64(buckets)).astype(np.int32)
    return keys, np.argsort(bucket, kind="stable"), np.concatenate(([0], np.cumsum(np.bincount(bucket, minlength=buckets))))


def dealt(chunks: DataFrame, buckets: int, counts_: bool, asks: bool) -> DataFrame:
    """What each chunk's words and bigrams occur in its target and background texts, a row for each bucket."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(len(b)):
                words, ids, counts = unpacked(b, k)
                codes, where = bigrams(counts, ids, len(words))
                keys, order, starts = keys_of(words, codes, buckets)
                flags = np.repeat(np.array(b.column("targets")[k].as_py(), dtype=bool), counts)
                total, hit = (np.concatenate((np.bincount(ids[f], minlength=len(words)), np.bincount(where[f], minlength=len(codes)))) for f in (slice(None), flags))
                t, o = (x[order] if counts_ else np.empty(0, dtype=np.int64) for x in (hit, total - hit))
                keys, chunk = keys[order], b.column("chunk")[k].as_py()
                some = np.flatnonzero(np.diff(starts))
                cut = lambda x, put: pa.array([put(x[starts[s] : starts[s + 1]]) for s in some], pa.binary())  # noqa: B023, E731
                cols = [pa.array(some.astype(np.int32)), pa.array([chunk] * len(some), pa.int64()), pa.array([asks] * len(some), pa.bool_()), cut(keys, np.ndarray.tobytes), cut(t, squeezed), cut(o, squeezed)]
                yield pa.RecordBatch.from_arrays(cols, names=[c.split()[0] for c in DEALT.split(", ")])

    return chunks.mapInArrow(count, DEALT)


def summed(rows: pa.Table) -> pa.Table:
    """The answers of one bucket, and a row without a chunk that tells its number of different words."""
    chunk, asks = rows.column("chunk").to_pylist(), rows.column("asks").to_pylist()
    keys = [np.frombuffer(x.as_buffer(), np.uint64) for x in rows.column("keys")]
    t, b = ([unsqueezed(x.as_buffer()) for x in rows.column(c)] for c in ("t", "b"))
    known, where = np.unique(np.concatenate([k if len(x) else k[:0] for k, x in zip(keys, t)]), return_inverse=True)
    sums = [np.bincount(where, weights=np.concatenate(x), minlength=len(known)).astype(np.int64) for x in (t, b)]
    word = known & np.uint64(1) == 0
    held = word | (sums[0] + sums[1] >= LEAST)
    bucket, out = rows.column("bucket")[0].as_py(), [(-1, int(word.sum()), b"", b"", b"")]
    for c, k, a in zip(chunk, keys, asks):
        if a and len(known):
            at = np.minimum(np.searchsorted(known, k), len(known) - 1)
            places = np.flatnonzero((known[at] == k) & held[at])
            if len(places):
                out.append((c, 0, squeezed(np.diff(places, prepend=0)), *(squeezed(x[at[places]]) for x in sums)))
    cols = list(zip(*out))
    kinds = [pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary()]
    c, n, *rest = [pa.array(x, k) for x, k in zip(cols, kinds)]
    return pa.Table.from_arrays([c, pa.array([bucket] * len(out), pa.int32()), n, *rest], names=[x.split()[0] for x in ANSWER.split(", ")])


def bucket_count(chunks: DataFrame) -> int:
    tokens = chunks.agg(F.coalesce(F.sum(F.aggregate("counts", F.lit(0).cast("long"), lambda x, y: x + y)), F.lit(0))).first()[0]
    return 1 + 2 * tokens // BUCKET_KEYS


def fitted(chunks: DataFrame, asks: bool) -> tuple[Models, DataFrame, int]:
    """The models, and the answers to their own chunks if these ask."""
    buckets = bucket_count(chunks)
    told = staged(dealt(chunks, buckets, True, asks).groupBy("bucket").applyInArrow(summed, ANSWER))
    words = told.agg(F.coalesce(F.sum("n_words"), F.lit(0))).first()[0]
    each = chunks.select(F.explode(F.arrays_zip("targets", "counts")).alias("d")).select("d.*")
    n = {r["targets"]: r for r in each.groupBy("targets").agg(F.count("*").alias("docs"), F.sum("counts").alias("tokens")).collect()}
    of = lambda c: tuple(n[k][c] if k in n else 0 for k in (True, False))
    return Models(chunks, words, of("tokens"), of("docs")), told, buckets


def train(rows: DataFrame) -> Models:
    return fitted(chunked(rows), False)[0]


def rated(chunks: DataFrame, told: DataFrame, buckets: int, models: Models) -> DataFrame:
    told = told.where("chunk >= 0").groupBy(F.col("chunk").alias("_chunk")).agg(F.collect_list(F.struct("bucket", "places", "t", "b")).alias("told"))
    rows = chunks.drop("targets").join(told, F.col("chunk") == F.col("_chunk"), "left").drop("_chunk")
    n_words, tokens, starts = models.words, np.array(models.tokens, dtype=float)[:, None], np.array(models.starts, dtype=float)[:, None]

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(len(b)):
                words, ids, counts = unpacked(b, k)
                codes, where = bigrams(counts, ids, len(words))
                keys, order, at = keys_of(words, codes, buckets)
                sums = np.zeros((2, len(keys)))
                for x in b.column("told")[k].as_py() or ():
                    where_ = order[at[x["bucket"]] + np.cumsum(unsqueezed(x["places"]))]
                    sums[:, where_] = unsqueezed(x["t"]), unsqueezed(x["b"])
                seen, both = sums[:, : len(words)], sums[:, len(words) :]
                unigram = (seen + 1.0) / (tokens + n_words + 1)
                history = np.concatenate((seen, starts), axis=1)
                before, word = codes // (len(words) + 1), codes % (len(words) + 1)
                losses = -np.log((both + WEIGHT * unigram[:, word]) / (history[:, before] + WEIGHT))
                doc = np.repeat(np.arange(len(counts)), counts)
                mean = [np.bincount(doc, weights=x[where], minlength=len(counts)) / np.maximum(counts, 1) for x in losses]
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_ids")[k].values, pa.array(counts), *map(pa.array, mean), pa.array(mean[0] - mean[1])],
                    names=["doc_id", "n_tokens", "loss_target", "loss_background", "score"],
                )

    return rows.mapInArrow(score, "doc_id long, n_tokens long, loss_target double, loss_background double, score double")


def scored(docs: DataFrame, models: Models) -> DataFrame:
    chunks = chunked(docs.select("doc_id", "text", F.lit(False).alias("target")))
    buckets = bucket_count(models.chunks)
    rows = dealt(models.chunks, buckets, True, False).unionByName(dealt(chunks, buckets, False, True))
    return rated(chunks, staged(rows.groupBy("bucket").applyInArrow(summed, ANSWER)), buckets, models)


def op10_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    chunks = chunked(flagged(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")))
    models, told, buckets = fitted(chunks, True)
    return rated(chunks, told, buckets, models)


ORACLE = None
