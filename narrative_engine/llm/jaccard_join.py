"""Exact n-gram Jaccard join in the metric space of shingle sets.

1. Texts that are equal collapse to the one with the smallest doc_id.
2. Regions.  Documents of unrelated texts are at distance 1 from each other, so document pivots
   alone would put nearly all of them on every boundary.  The first pivots are therefore sets of
   shingles: sizes fall into shells no pair within the radius can skip, a shell cuts the shingle
   universe into more classes than two of its documents within the radius may differ in, and a
   document stands in the cell of each of its class parts.  By counting, every pair within the
   radius agrees on a whole class part, so it meets in at least one region; documents next to a
   shell's border are replicated into the next shell.
3. Inside a region a document is the pivot.  Its distances to the members are exact; members
   within the radius ``r`` are linked.  By the triangle inequality no member beyond ``2r`` links
   to one within ``r``, so the region splits in an outer part (beyond ``r``) and an inner one (up
   to ``2r``, kept only if its rim holds any), and both are joined the same way until all members
   of a part are in one component.  What is left after ``ROUNDS`` meets on rare shingles, and pairs
   of different components that their sizes and places allow are compared.
4. Links become components.

Defined results: null and blank texts have an empty set and link with nothing.  Every row has the
size of its own text's set.  Rows that share a doc_id are one document, so its component holds
whatever any of its texts links with; a text without a doc_id links like any other, and its
component is the smallest doc_id in reach, null if there is none.  Repeated rows give equal rows; an
empty table gives no rows.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from narrative_engine.llm.common import staged, table
from narrative_engine.llm.components import components
from narrative_engine.llm.shingles import mix, sets
from narrative_engine.shipping import ship

SIZE, NUM, DEN = 4, 85, 100  # shingle words; a link: DEN * common >= NUM * union
ROUNDS = 1
#: A list of ids is broadcast up to this many, and joined by shuffle beyond.
BROADCAST_IDS = 1_000_000


@functools.lru_cache(maxsize=64)
def shells(num: int, den: int, upto: int) -> np.ndarray:
    """Largest size of each shell; a pair within the radius lies in one shell or in neighbours."""
    tops = [1]
    while tops[-1] < upto:
        tops.append(max(tops[-1] + 1, tops[-1] * den // num))
    return np.array(tops, dtype=np.int64)


def classes(top: int, num: int, den: int) -> tuple[int, int]:
    """How many classes a shell with this largest size needs, and how many may be empty unharmed."""
    differ = 2 * top * (den - num) // (den + num)
    if differ == 0:
        return 1, 0
    spare = -(-3 * differ // 100) + 1
    return differ + 1 + spare, spare


def region_keys(h: np.ndarray, num: int = NUM, den: int = DEN) -> np.ndarray:
    """Keys of the regions in which the set ``h`` stands; sets within the radius share one."""
    n = len(h)
    if not n:
        return np.empty(0, dtype=np.int64)
    tops = shells(num, den, 1 << max(4, (n * 2 - 1).bit_length()))
    own = int(np.searchsorted(tops, n))
    value, out = mix(h), []
    for shell in (own, own + 1):
        m, spare = classes(int(tops[shell]), num, den)
        part = (h % np.uint64(m)).astype(np.int64)
        sums = np.zeros(m, dtype=np.uint64)
        np.add.at(sums, part, value)
        held = np.bincount(part, minlength=m) > 0
        tag = mix(np.arange(m, dtype=np.uint64) + np.uint64((shell + 1) << 40))
        out.append(mix(sums[held] + tag[held]))
        if m - int(held.sum()) > spare:  # two such sets may agree on empty parts only: prefixes of the hash order
            prefix = n - -(-num * n // den) + 1
            out.append(mix(h[:prefix] + np.uint64((shell + 1) * 0xA24BAED4963EE407 & 0xFFFFFFFFFFFFFFFF)))
    return np.unique(np.concatenate(out)).view(np.int64)


def keyed(docs: DataFrame, size: int, num: int, den: int) -> DataFrame:
    """Set size and region keys of each document."""

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, len(b), 256):
                part = b.slice(at, 256)
                found = sets(part.column(1), size)
                keys = [region_keys(h, num, den) for h in found]
                flat = np.concatenate(keys) if keys else np.empty(0, dtype=np.int64)
                ends = np.concatenate(([0], np.cumsum([len(k) for k in keys]))).astype(np.int32)
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array([len(h) for h in found], pa.int64()), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))],
                    names=["doc_id", "n", "keys"],
                )

    return docs.select("doc_id", "text").mapInArrow(build, "doc_id long, n long, keys array<long>")


def set_bytes(docs: DataFrame, size: int) -> DataFrame:
    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, len(b), 256):
                part = b.slice(at, 256)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([h.tobytes() for h in sets(part.column(1), size)], pa.binary())], names=["id", "items"])

    return docs.select("doc_id", "text").mapInArrow(build, "id long, items binary")


def by_ids(docs: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """Semi or anti join on a list of ids, which is broadcast only when it is short."""
    short = ids.count() <= BROADCAST_IDS
    return docs.join(F.broadcast(ids) if short else ids, docs["doc_id"] == ids["id"], how)


def measured(pairs: DataFrame, items: DataFrame) -> DataFrame:
    """(p, x, common, total): exact intersection and union sizes of pairs of ids."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            common, total = [], []
            for x, y in zip(b.column(2), b.column(3)):
                one, two = np.frombuffer(x.as_buffer(), dtype=np.uint64), np.frombuffer(y.as_buffer(), dtype=np.uint64)
                if len(one) > len(two):
                    one, two = two, one
                at = np.searchsorted(two, one)
                same = int((two[np.minimum(at, len(two) - 1)] == one).sum()) if len(two) else 0
                common.append(same)
                total.append(len(one) + len(two) - same)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(common, pa.int64()), pa.array(total, pa.int64())], names=["p", "x", "common", "total"])

    first = pairs.join(items, F.col("x") == F.col("id")).select("p", "x", F.col("items").alias("one"))
    both = first.join(items, F.col("p") == F.col("id")).select("p", "x", "one", F.col("items").alias("two"))
    return both.mapInArrow(compare, "p long, x long, common long, total long")


def within(num: int, den: int):
    return den * F.col("common") >= num * F.col("total")


def rare_cells(left: DataFrame, items: DataFrame, num: int, den: int) -> DataFrame:
    """Cells (t, x, c, n, rest) of the shingles that documents (x, c) may still meet on.

    With its shingles ordered by how many of these documents have them, a document meets any other
    within the radius on one of its first n - ceil(num/den n) + 1; those it has alone meet nobody.
    ``rest`` is the number of its shingles from that one on.
    """

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [np.frombuffer(v.as_buffer(), dtype=np.int64) for v in b.column(2)]
            ends = np.concatenate(([0], np.cumsum([len(f) for f in found]))).astype(np.int32)
            flat = np.concatenate(found) if found else np.empty(0, dtype=np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))], names=["x", "c", "items"])

    held = left.join(items, F.col("x") == F.col("id")).select("x", "c", "items").mapInArrow(split, "x long, c long, items array<long>")
    rows = staged(held.select("x", "c", F.size("items").cast("long").alias("n"), F.explode("items").alias("t")))
    often = staged(rows.groupBy("t").agg(F.count("*").alias("df")).where("df > 1"))
    shared = rows.join(often, "t").groupBy("x", "c", "n").agg(F.array_sort(F.collect_list(F.struct("df", "t"))).alias("s"))
    prefix = F.col("n") - F.ceil(F.col("n") * num / den) + 1
    first = F.slice("s", 1, F.greatest(prefix - (F.col("n") - F.size("s")), F.lit(0)).cast("int"))
    placed = shared.select("x", "c", "n", F.size("s").alias("m"), F.posexplode(first).alias("at", "f"))
    return placed.select(F.col("f.t").alias("t"), "x", "c", "n", (F.col("m") - F.col("at")).cast("long").alias("rest"))


#: Sizes of a band differ by about this part.
BAND = 0.02


def rare_pairs(cells: DataFrame, num: int, den: int) -> DataFrame:
    """Pairs (p, x) of different components that may be within the radius by their sizes and places.

    Two sets within it have ``num/(num + den)`` of the sum of their sizes in common.  At their first
    common shingle no more than ``rest`` of either can be, which bounds the partner's size.  So the
    larger set asks only in the bands of sizes left to it, and the smaller one stands in its own
    band only while it could meet a set of its size: near copies with edits of their own drop out
    as rows, before the join, however large their group.
    """
    band = lambda size, pad: F.floor((F.log(size.cast("double")) + pad) / BAND)
    least = F.floor((F.col("n") * num + den - 1) / den)
    most = F.least("n", F.floor(F.col("rest") * (num + den) / num) - F.col("n"))
    asking = cells.withColumn("lo", least).withColumn("hi", most).where("hi >= lo")
    asking = asking.select("t", F.col("x").alias("p"), F.col("c").alias("cp"), F.col("n").alias("np"), F.col("rest").alias("rp"), F.explode(F.sequence(band(F.col("lo"), -1e-9), band(F.col("hi"), 1e-9))).alias("band"))
    standing = cells.where(F.col("rest") * (num + den) >= F.col("n") * 2 * num).select("t", "x", "c", "n", "rest", band(F.col("n"), 0.0).alias("band"))
    fits = (F.least("rp", "rest") * (num + den) >= (F.col("np") + F.col("n")) * num) & ((F.col("n") < F.col("np")) | ((F.col("n") == F.col("np")) & (F.col("x") < F.col("p"))))
    return asking.join(standing, ["t", "band"]).where((F.col("cp") != F.col("c")) & fits).select("p", "x").distinct()


#: Rows of a partition of the small tables of the rounds.
PART_ROWS = 200_000


def links(live: DataFrame, items: DataFrame, num: int, den: int, rounds: int = ROUNDS) -> tuple[DataFrame, DataFrame]:
    """Links (a, b), and the components (node, root) of all pairs within the radius in the regions (key, x)."""
    spark = live.sparkSession
    size = lambda n: max(spark.sparkContext.defaultParallelism, n // PART_ROWS + 1)
    found = root = None
    part, n = live.select("key", "x"), live.count()
    for k in range(rounds):
        # first the smallest id, which regions share; then one by chance in each region, so that a
        # document meets other pivots in each of its regions and large groups of near copies join soon
        order = F.struct("x") if k == 0 else F.struct(F.xxhash64("key", "x"), "x")
        centre = part.groupBy("key").agg(F.min(order).getField("x").alias("p"))
        seen = staged(part.join(centre, "key").where("x <> p").select("key", "x", "p"), size(n))
        if not (n := seen.count()):
            break
        dist = staged(measured(staged(seen.select("p", "x").distinct(), size(n)), items), size(n))
        new = dist.where(within(num, den)).select(F.col("p").alias("a"), F.col("x").alias("b"))
        if found is None:
            found = staged(new)
            root = components(found)
        elif not new.isEmpty():
            found = staged(found.unionByName(new))
            # the stars so far stand for the links before
            root = components(root.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(new))
        # twice the radius: 1 - common/total <= 2 (1 - num/den)
        near = (F.col("common") * den) >= (F.col("total") * (2 * num - den))
        told = staged(seen.join(dist, ["p", "x"]).select("key", "x", within(num, den).alias("linked"), near.alias("near")), size(n))
        kind = told.groupBy("key").agg(F.max(F.col("near") & ~F.col("linked")).alias("rim"), F.max(~F.col("near")).alias("far"))
        told = told.join(kind, "key")
        # without far members the inner part holds the outer one
        outer = told.where("NOT linked AND far").select(F.xxhash64("key", F.lit(0)).alias("key"), "x")
        inner = told.where("near AND rim").select(F.xxhash64("key", F.lit(1)).alias("key"), "x")
        rest = outer.unionByName(inner).join(root, F.col("x") == F.col("node"), "left").select("key", "x", F.coalesce("root", "x").alias("c"))
        rest = staged(rest, size(n))
        open_ = rest.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi").select("key")
        part = staged(rest.join(open_, "key", "left_semi"), size(n))
        if not (n := part.count()):
            break
    if found is None:
        none = live.select(F.col("x").alias("a"), F.col("x").alias("b")).limit(0)
        return none, none.select(F.col("a").alias("node"), F.col("b").alias("root"))
    if n and "c" in part.columns:  # different components that the rounds have left in one region
        cells = staged(rare_cells(part.select("x", "c").distinct(), items, num, den), size(n))
        last = staged(rare_pairs(cells, num, den), size(n))
        new = staged(measured(last, items).where(within(num, den)).select(F.col("p").alias("a"), F.col("x").alias("b")), size(n))
        if not new.isEmpty():
            found = staged(found.unionByName(new))
            root = components(root.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(new))
    return found, root


def identified(docs: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame, bool]:
    """``kept`` (doc_id, same), ``nodes`` (same, rep, copies, x) with a row per different text, its texts (doc_id = x, text), and whether
    doc_ids fall short of naming the texts.

    ``x`` names a text: its smallest doc_id, or a number beyond all doc_ids where that is null or
    names several texts.  The numbers are written with the table, so they are the same wherever it is read.
    """
    texts = docs.select(F.col("doc_id").cast("long"), "text")
    same = F.unhex(F.md5(F.coalesce(F.col("text"), F.lit("")).cast("binary")))
    kept = staged(texts.select("doc_id", same.alias("same")))
    first = staged(kept.groupBy("same").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies")))
    clash = staged(first.groupBy("rep").agg(F.count("*").alias("n")).where("n > 1 OR rep IS NULL").select("rep"))
    if clash.isEmpty():
        nodes = first.withColumn("x", F.col("rep"))
        copies = staged(kept.join(first.where("copies > 1"), "same").where("doc_id <> rep").select(F.col("doc_id").alias("id")))
        return kept, nodes, by_ids(texts, copies, "left_anti"), False
    most = kept.agg(F.coalesce(F.max("doc_id"), F.lit(0))).first()[0]
    odd = first.join(clash.select(F.col("rep").alias("r")), F.col("rep").eqNullSafe(F.col("r"))).select("same", F.col("rep").alias("_r"), (F.lit(most + 1) + F.monotonically_increasing_id()).alias("_x"))
    odd = staged(odd)
    nodes = first.join(odd.select("same", "_x"), "same", "left").select("same", "rep", "copies", F.coalesce("_x", "rep").alias("x"))
    copies = kept.join(first.where("copies > 1"), "same").where("doc_id <> rep").select(F.col("doc_id").alias("id"))
    gone = staged(copies.unionByName(clash.where("rep IS NOT NULL").select(F.col("rep").alias("id"))).distinct())
    plain = by_ids(texts.where("doc_id IS NOT NULL"), gone, "left_anti")
    rest = by_ids(texts, clash.where("rep IS NOT NULL").select(F.col("rep").alias("id")), "left_semi").unionByName(texts.where("doc_id IS NULL"))
    rest = rest.withColumn("same", same).join(odd, "same").where(F.col("doc_id").eqNullSafe(F.col("_r")))
    rest = rest.dropDuplicates(["same"]).select(F.col("_x").alias("doc_id"), "text")
    return kept, nodes, plain.unionByName(rest), True


def joined(docs: DataFrame, size: int = SIZE, num: int = NUM, den: int = DEN) -> DataFrame:
    """doc_id, same, n_shingles, component_id (the smallest reachable doc_id), n_links and stays of each row.

    ``n_links`` counts the verified links that the component was built from; ``same`` is a hash of
    the text, and ``stays`` is true for the texts that stand for their group of linked texts: the
    one with the smallest doc_id (and hash).
    """
    ship(docs.sparkSession)
    kept, nodes, reps, several = identified(docs)
    marked = staged(keyed(reps, size, num, den))

    cells = marked.select(F.explode("keys").alias("key"), F.col("doc_id").alias("x"))
    full = staged(cells.groupBy("key").agg(F.min("x").alias("lo"), F.max("x").alias("hi")).where("lo <> hi").select("key"))
    live = staged(cells.join(full, "key", "left_semi").distinct())  # the rows of a key are split where it is hot
    asked = staged(live.select(F.col("x").alias("id")).distinct())
    items = staged(set_bytes(by_ids(reps, asked, "left_semi"), size).groupBy("id").agg(F.first("items").alias("items")))
    found, root = links(live, items, num, den)
    ends = found.select(F.explode(F.array("a", "b")).alias("id")).groupBy("id").agg(F.count("*").alias("n_links"))

    by_x = marked.select(F.col("doc_id").alias("x"), "n").groupBy("x").agg(F.first("n").alias("n_shingles"))
    by_x = by_x.join(root, F.col("x") == F.col("node"), "left").join(ends, F.col("x") == F.col("id"), "left")
    by_x = by_x.select("x", "n_shingles", F.coalesce("root", "x").alias("root"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))
    if not several:  # a text's name is its smallest doc_id
        by_x = by_x.select("x", "n_shingles", "n_links", F.col("root").alias("component_id"), (F.col("root") == F.col("x")).alias("leads"))
    else:
        by_x = staged(by_x)
        of = staged(nodes.join(by_x.select("x", "root"), "x").select("same", "rep", "x", "root"))
        leader = of.groupBy("root").agg(F.min(F.struct(F.col("rep").isNull(), "rep", "same", "x")).getField("x").alias("lead"))
        # a doc_id with several texts joins their groups
        full_ids = kept.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.min("same").alias("one"), F.max("same").alias("two")).where("one <> two").select("doc_id")
        ties = kept.join(full_ids, "doc_id").join(of.select("same", "root"), "same").join(by_x.where("n_shingles > 0").select(F.col("x").alias("root")), "root", "left_semi")
        low = ties.groupBy("doc_id").agg(F.min("root").alias("a"))
        ties = staged(ties.join(low, "doc_id").select("a", F.col("root").alias("b")).where("a <> b").distinct())
        tied = components(ties).select(F.col("node").alias("root"), F.col("root").alias("top"))
        whole = of.join(tied, "root", "left").withColumn("top", F.coalesce("top", "root"))
        # the doc_ids of all copies, not only the smallest of each text
        least = whole.groupBy("top").agg(F.min("rep").alias("component_id"))
        by_root = whole.select("root", "top").distinct().join(least, "top").join(leader, "root").select("root", "component_id", "lead")
        by_x = by_x.join(by_root, "root").select("x", "n_shingles", "n_links", "component_id", (F.col("lead") == F.col("x")).alias("leads"))
    rows = kept.join(nodes.select("same", "rep", "x"), "same").join(staged(by_x), "x", "left")
    alone = F.col("n_shingles") == 0
    return rows.select(
        "doc_id", "same", F.col("n_shingles").cast("long").alias("n_shingles"), F.when(alone, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"), "n_links",
        (alone | (F.col("leads") & F.col("doc_id").eqNullSafe(F.col("rep")))).alias("stays"),
    )


def representatives(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stand for their group; a text without words is a group of its own, and so is each row of it."""
    groups = staged(joined(docs))
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_doc"))  # out of the way of the names below
    doc_id, same = F.col("_doc.doc_id").cast("long"), F.unhex(F.md5(F.coalesce(F.col("_doc.text"), F.lit("")).cast("binary")))
    this = doc_id.eqNullSafe(F.col("_id")) & (same == F.col("_same"))

    def listed(which: DataFrame) -> DataFrame:
        which = staged(which.select(F.col("doc_id").alias("_id"), F.col("same").alias("_same")))
        return F.broadcast(which) if which.count() <= BROADCAST_IDS else which

    left = rows.join(listed(groups.where("NOT stays").select("doc_id", "same").distinct()), this, "left_anti")
    twice = groups.where("stays AND n_shingles > 0").groupBy("doc_id", "same").count().where("count > 1")
    if twice.isEmpty():
        return left.select("_doc.*")
    twice = listed(twice)
    once = left.join(twice, this, "left_semi").withColumns({"_id": doc_id, "_same": same}).dropDuplicates(["_id", "_same"]).select("_doc")
    return left.join(twice, this, "left_anti").unionByName(once).select("_doc.*")


def op6_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return joined(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")


ORACLE = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (
  SELECT DISTINCT doc_id, array_to_string(w[i:i+3], ' ') AS g
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
l AS (
  SELECT a.doc_id AS x, b.doc_id AS y FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id JOIN n na ON na.doc_id = a.doc_id JOIN n nb ON nb.doc_id = b.doc_id
  GROUP BY a.doc_id, b.doc_id, na.n, nb.n HAVING 100 * count(*) >= 85 * (na.n + nb.n - count(*))),
c(x, root) AS (SELECT doc_id, doc_id FROM n UNION SELECT l.y, c.root FROM c JOIN l ON l.x = c.x WHERE c.root < l.y),
r AS (SELECT x, min(root) AS root FROM c GROUP BY x)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, coalesce(r.root, d.doc_id) AS component_id
FROM d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN r ON r.x = d.doc_id
"""
