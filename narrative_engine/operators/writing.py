"""Prompts, exemplars and the deterministic writer.

The writer stands in for a hosted model behind the same frame: it fills the slots of the exemplars
in a prompt, so a narrative inherits their rounding, omissions and wording.  Exemplars are samples,
pairs of an explanation and a narrative, with the slots that reading them gives
(:mod:`narrative_engine.operators.samples`).  Without exemplars it writes the long neutral prose that
a base prompt asks for.  Everything is a column expression.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Protocol

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from narrative_engine.fixtures import CLAUSES, STYLE_PARTS, ZERO_SHOT
from narrative_engine.operators import samples
from narrative_engine.operators.columns import let, uniform
from narrative_engine.operators.explanation import EXPLANATION_KINDS, number_text, serialize_explanation
from narrative_engine.settings import BASE_PROMPTS, CUE, DOMAINS, OUTPUT_RULES, STYLES, TECHNIQUES
from narrative_engine.shipping import ship

CLAUSE = "struct<c:string,up:string,down:string>"
EX = f"struct<ex:string,expl_text:string,text:string,lead:string,joiner:string,tail:string,omits:boolean,clauses:array<{CLAUSE}>>"


def about(x: Column) -> Column:
    """Two leading digits or so: within five hundredths of ``x``."""
    whole = lambda k: (F.floor(x / k + 0.5) * k).cast("bigint").cast("string")
    return F.when(x >= 10000, whole(1000)).when(x >= 1000, whole(100)).when(x >= 100, whole(10)).when(x >= 10, whole(1)).otherwise(number_text(x))


def coarse(x: Column) -> Column:
    """A third too much: what careless rounding does."""
    return number_text(F.floor(x * 140 + 1.0) / 100)


def filled(x: Column, clause: Column) -> Column:
    """A clause (c, up, down) with the slots of feature ``x``; a number is only worded where its slot is."""
    size = F.abs(x["contribution"])
    numbers = (("{c}", number_text(size)), ("{r}", about(size)), ("{k}", coarse(size)), ("{t}", F.format_number(F.floor(size + 0.5), 0)))

    def with_direction(told: Column) -> Column:
        out = told
        for slot, text in numbers:
            out = F.replace(out, F.lit(slot), F.when(F.contains(told, F.lit(slot)) | size.isNull(), text).otherwise(""))
        return F.replace(F.replace(out, F.lit("{v}"), x["value"]), F.lit("{f}"), x["feature"])

    return let(F.replace(clause["c"], F.lit("{d}"), F.when(x["contribution"] < 0, clause["down"]).otherwise(clause["up"])), with_direction)


def followed(exemplars: Column, n: Column) -> Column:
    """The clauses of a narrative of ``n`` features: the k-th follows exemplar k mod their number, in its k-th clause or its last."""
    def at(i: Column) -> Column:
        e = F.get(exemplars, i % F.size(exemplars))
        return F.get(e["clauses"], F.least(i, F.size(e["clauses"]) - 1))

    return F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), at)).otherwise(F.array().cast(f"array<{CLAUSE}>"))


def told_features(expl: Column, omits: Column) -> Column:
    return F.size(expl) - F.when(omits & (F.size(expl) > 1), 1).otherwise(0)


def joined_clauses(expl: Column, clauses: Column, lead: Column, joiner: Column, tail: Column) -> Column:
    parts = F.transform(clauses, lambda c, i: filled(F.get(expl, i), c))
    return F.concat(lead, F.replace(F.array_join(parts, "\x01"), F.lit("\x01"), joiner), tail)


def realized(expl: Column, exemplars: Column) -> Column:
    """The narrative in the way of ``exemplars``; lead, joiner and tail are the first one's."""
    def with_first(first: Column) -> Column:
        return joined_clauses(expl, followed(exemplars, told_features(expl, first["omits"])), first["lead"], first["joiner"], first["tail"])

    return let(F.get(exemplars, F.lit(0)), with_first)


def zero_shot_exemplar(base: str) -> Column:
    """The base prompt's prose as an exemplar without a sample."""
    lead, slots, up, down, joiner, tail = ZERO_SHOT[base]
    clause = F.struct(F.lit(slots).alias("c"), F.lit(up).alias("up"), F.lit(down).alias("down"))
    return F.struct(
        F.lit("zero").alias("ex"), F.lit("").alias("expl_text"), F.lit("").alias("text"), F.lit(lead).alias("lead"), F.lit(joiner).alias("joiner"), F.lit(tail).alias("tail"),
        F.lit(False).alias("omits"), F.array(clause).alias("clauses"),
    )


def zero_shot(expl: Column, base: str = "plain") -> Column:
    return realized(expl, F.array(zero_shot_exemplar(base)))


def authored(entries: DataFrame) -> DataFrame:
    """The hand-written narratives: the first five entries of each style, as its author words them."""
    spark = entries.sparkSession
    rows = [(s, k + 1, *(STYLE_PARTS[s][i] for i in (0, 3, 4)), flaw == "omits", [(c, STYLE_PARTS[s][1], STYLE_PARTS[s][2])]) for s in STYLES for k, (c, flaw) in enumerate(CLAUSES[s])]
    own = spark.createDataFrame(rows, f"style string, place int, lead string, joiner string, tail string, omits boolean, clauses array<{CLAUSE}>")
    one = F.array(F.struct("lead", "joiner", "tail", "omits", "clauses"))
    return entries.join(F.broadcast(own), ["style", "place"]).select("style", "domain", "row_id", "place", "expl", realized(F.col("expl"), one).alias("text"))


def style_frame(hand: DataFrame) -> DataFrame:
    """style, domain and its hand-written exemplars, read from their narratives; nine rows, always broadcast.

    The samples are five a style, so the driver reads them.
    """
    spark = hand.sparkSession
    got = hand.select("style", "place", serialize_explanation("expl").alias("expl_text"), "text").orderBy("style", "place").collect()
    rows = [(s, STYLES[s][0], [samples.as_row(samples.derived(str(r["place"]), r["expl_text"], r["text"])) for r in got if r["style"] == s]) for s in STYLES]
    return spark.createDataFrame(rows, f"style string, domain string, hand array<{EX}>")


def technique_frame(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(TECHNIQUES), "technique int, base string, h int, b int")


def entries(spark: SparkSession, explained: dict[str, DataFrame], whole: bool = False) -> DataFrame:
    """style, domain, row_id, place, expl: each style's own draw of its domain's rows, in md5 order.

    With ``whole`` every row of the domain is an entry (place 0), as in bulk use.
    """
    out = None
    for domain, frame in explained.items():
        own = [(s, n) for s, (d, n, _) in STYLES.items() if d == domain]
        each = F.explode(F.array(*[F.struct(F.lit(s).alias("style"), F.lit(n).alias("quota")) for s, n in own]))
        rows = frame.select("row_id", "expl").withColumn("_s", each).select(F.col("_s.style").alias("style"), F.lit(domain).alias("domain"), "row_id", "expl", F.col("_s.quota").alias("quota"))
        if whole:
            rows = rows.withColumn("place", F.lit(0))
        else:
            key = F.md5(F.concat("style", F.lit("|"), "row_id").cast("binary"))
            rows = rows.withColumn("place", F.row_number().over(Window.partitionBy("style").orderBy(key, "row_id")))
            rows = rows.where("place <= quota AND place <= 35")  # the bound lets the rank limit act before the shuffle
        rows = rows.drop("quota")
        out = rows if out is None else out.unionByName(rows)
    return out


def drawn(pool: Column, n: Column, kind: str) -> Column:
    """``n`` members of a pool, each with its md5 key, by the md5 order of this prompt; all of them when there are fewer."""
    keyed = F.transform(pool, lambda x: F.struct(F.md5(F.concat(F.col("style"), F.lit("|"), F.col("row_id"), F.lit(f"|{kind}"), x["ex"].cast("string")).cast("binary")).alias("k"), x.alias("x")))
    return F.slice(F.array_sort(keyed), 1, F.least(n, F.size(pool)))


def sample_exemplars(df: DataFrame) -> DataFrame:
    """``exemplars``: H hand-written and B bootstrapped ones of the row's style, drawn and mixed for this prompt; all where there are fewer."""
    both = F.concat(drawn(F.col("hand"), F.col("h"), "h"), drawn(F.col("boot"), F.col("b"), "b"))
    return df.withColumn("exemplars", F.transform(F.array_sort(both), lambda s: s["x"]))


def drawn_places(df: DataFrame) -> DataFrame:
    """``hand_drawn`` and ``boot_drawn``: (k, at) of each pool's members in the order of :func:`drawn`; ``at`` is the place in ``hand`` followed by ``boot``.

    ``df`` has style, row_id and the pools' names, ``hand_ex`` and ``boot_ex``.
    """
    def keyed(names: str, kind: str, before: Column) -> Column:
        key = lambda ex: F.md5(F.concat(F.col("style"), F.lit("|"), F.col("row_id"), F.lit(f"|{kind}"), ex).cast("binary"))
        return F.array_sort(F.transform(names, lambda ex, i: F.struct(key(ex).alias("k"), (before + i).alias("at"))))

    return df.withColumns({"hand_drawn": keyed("hand_ex", "h", F.lit(0)), "boot_drawn": keyed("boot_ex", "b", F.size("hand_ex"))})


def pool_parts(styles: DataFrame) -> DataFrame:
    """A style's exemplars, ``hand`` followed by ``boot``, as parts with numbers; equal parts have one number.

    ``firsts`` and ``clauses`` are the different parts: all that an exemplar gives as the first one,
    and the clauses.  ``first_of``, ``omits_of`` and ``clauses_of`` have those of each exemplar.
    """
    pool = F.concat("hand", "boot")
    first = lambda x: F.struct(x["lead"].alias("lead"), x["joiner"].alias("joiner"), x["tail"].alias("tail"), x["omits"].alias("omits"))
    rows = styles.select("style", *[F.transform(p, lambda x: x["ex"]).alias(f"{p}_ex") for p in ("hand", "boot")], pool.alias("_pool"))
    rows = rows.withColumns({"firsts": F.array_distinct(F.transform("_pool", first)), "clauses": F.array_distinct(F.flatten(F.transform("_pool", lambda x: x["clauses"])))})
    number = lambda parts, x: (F.array_position(parts, x) - 1).cast("int")
    return rows.withColumns({
        "first_of": F.transform("_pool", lambda x: number(F.col("firsts"), first(x))), "omits_of": F.transform("_pool", lambda x: x["omits"]),
        "clauses_of": F.transform("_pool", lambda x: F.transform(x["clauses"], lambda c: number(F.col("clauses"), c))),
    }).drop("_pool")


def used_parts(h: int, b: int) -> Column:
    """What a narrative takes from ``h`` hand-written and ``b`` bootstrapped exemplars: the number of the first one's part, then of the clause that each told feature follows; none without exemplars."""
    some = lambda c, n: F.slice(c, 1, F.least(F.lit(n), F.size(c)))
    mixed = F.transform(F.array_sort(F.concat(some("hand_drawn", h), some("boot_drawn", b))), lambda s: s["at"])

    def parts(m: Column) -> Column:
        first, n = F.get(m, F.lit(0)), told_features(F.col("expl"), F.get("omits_of", F.get(m, F.lit(0))))
        own = lambda i: let(F.get("clauses_of", F.get(m, i % F.size(m))), lambda cs: F.get(cs, F.least(i, F.size(cs) - 1)))
        told = F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), own)).otherwise(F.array().cast("array<int>"))
        return F.when(F.size(m) == 0, F.array().cast("array<int>")).otherwise(F.concat(F.array(F.get("first_of", first)), told))

    return let(mixed, parts)


def of_parts(used: Column) -> Column:
    """The exemplar made of the parts that :func:`used_parts` numbers, as an array; none of none."""
    first = F.get("firsts", F.get(used, F.lit(0)))
    clauses = F.transform(F.slice(used, 2, F.greatest(F.size(used) - 1, F.lit(0))), lambda k: F.get("clauses", k))
    one = F.struct(F.lit("parts").alias("ex"), F.lit("").alias("expl_text"), F.lit("").alias("text"), *[first[c].alias(c) for c in ("lead", "joiner", "tail", "omits")], clauses.alias("clauses"))
    return F.filter(F.array(one.cast(EX)), lambda x: F.size(used) > 0)


def write(df: DataFrame) -> DataFrame:
    """``text`` of rows that have a technique's base prompt and ``exemplars``; without exemplars in the base prompt's own prose."""
    bare = F.coalesce(*[F.when(F.col("base") == b, F.array(zero_shot_exemplar(b))) for b in ZERO_SHOT])
    rows = df.withColumn("_used", F.when(F.size("exemplars") == 0, bare).otherwise(F.col("exemplars")))
    return rows.withColumn("text", realized(F.col("expl"), F.col("_used"))).drop("_used")


def build_prompt(df: DataFrame, kind: str = "contributions", extras: Column | None = None) -> DataFrame:
    """``prompt``: base, meaning of the inputs, exemplars, explanation, format, context, rules and cue.

    Exemplars stand as pairs, their explanation and their narrative.  ``kind`` names the kind of
    explanation; ``extras`` (map feature -> text) adds a field to every feature of this row.
    """
    base = F.create_map(*[F.lit(v) for kv in BASE_PROMPTS.items() for v in kv])
    context = F.create_map(*[F.lit(v) for d in DOMAINS.values() for v in (d.name, d.context)])
    pair = lambda x: F.concat(F.lit("Explanation: "), x["expl_text"], F.lit("\n" + CUE + " "), x["text"])
    shown = F.array_join(F.transform("exemplars", pair), "\n")
    own = serialize_explanation("expl", extras) if kind.startswith("contributions") else EXPLANATION_KINDS[kind].serialize(F.col("expl"))
    prompt = F.concat_ws(
        "\n", base[F.col("base")], F.lit("You get an explanation, its format and its context."), F.when(F.size("exemplars") > 0, F.concat(F.lit("Examples:\n"), shown)),
        F.concat(F.lit("Explanation: "), own), F.lit("Format: " + EXPLANATION_KINDS[kind].describe),
        F.concat(F.lit("Context: "), F.coalesce(context[F.col("domain")], F.lit(""))), F.lit(OUTPUT_RULES), F.lit(CUE),
    )
    return df.withColumn("prompt", prompt)


class TextBackend(Protocol):
    """Any model: prompts in, texts out, one batch at a time."""

    def complete(self, prompts: list[str]) -> list[str]: ...


class RemoteBackend:
    """A model behind an HTTP endpoint that takes {"prompts": [...]} and gives {"texts": [...]}.

    Requests that fail are tried again after growing pauses; nothing calls it unless a user names an
    endpoint.
    """

    def __init__(self, endpoint: str, batch: int = 16, tries: int = 4, pause: float = 0.5, timeout: float = 60.0, headers: dict[str, str] | None = None) -> None:
        self.endpoint, self.batch, self.tries, self.pause, self.timeout, self.headers = endpoint, batch, tries, pause, timeout, headers or {}

    def complete(self, prompts: list[str]) -> list[str]:
        import json
        import time
        import urllib.request

        out: list[str] = []
        for at in range(0, len(prompts), self.batch):
            part = prompts[at : at + self.batch]
            request = urllib.request.Request(self.endpoint, json.dumps({"prompts": part}).encode(), {"Content-Type": "application/json", **self.headers})
            for k in range(self.tries):
                try:
                    with urllib.request.urlopen(request, timeout=self.timeout) as answer:
                        texts = json.load(answer)["texts"]
                    break
                except OSError:
                    if k == self.tries - 1:
                        raise
                    time.sleep(self.pause * 2**k)
            if len(texts) != len(part):
                raise ValueError(f"{len(part)} prompts, {len(texts)} texts")
            out += texts
        return out


def plan_calls(df: DataFrame) -> DataFrame:
    """Each different prompt once, by hash: what a paid backend has to answer."""
    return df.select(F.sha2("prompt", 256).alias("prompt_hash"), "prompt").dropDuplicates(["prompt_hash"])


def replayed(df: DataFrame, cache: DataFrame) -> DataFrame:
    """``text`` from recorded answers (prompt_hash, answer); null where none is recorded."""
    return df.drop("text").withColumn("prompt_hash", F.sha2("prompt", 256)).join(cache.select("prompt_hash", F.col("answer").alias("text")), "prompt_hash", "left")


def completed(calls: DataFrame, make: Callable[[], TextBackend]) -> DataFrame:
    """(prompt_hash, answer) from a backend that every task makes for itself; answers are keyed by prompt, so a retry repeats no harm."""
    ship(calls.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        backend = make()
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(backend.complete(b.column(1).to_pylist()), pa.string())], names=["prompt_hash", "answer"])

    return calls.select("prompt_hash", "prompt").mapInArrow(run, "prompt_hash string, answer string")


#: Pairs of phrases that the noisy backend swaps.
SWAPS = (("more likely", "less likely"), ("raises", "lowers"), ("higher estimate", "lower estimate"))


def noisy(df: DataFrame, p: float = 0.3, seed: int = 7) -> DataFrame:
    """``text`` with seeded mistakes: every direction turned round in a share ``p`` of the rows."""
    text = F.col("text")
    for up, down in SWAPS:
        text = F.replace(F.replace(F.replace(text, F.lit(up), F.lit("\x02")), F.lit(down), F.lit(up)), F.lit("\x02"), F.lit(down))
    wrong = uniform(str(seed), F.col("style"), F.col("row_id")) < p
    return df.withColumn("mistake", wrong).withColumn("text", F.when(wrong, text).otherwise(F.col("text")))


def direct_explain(df: DataFrame, numeric: list[str], n: int = 3) -> DataFrame:
    """The baseline without attributions: ``guess`` names the features farthest from their mean, ``text`` tells the direction that their side of it suggests."""
    stats = df.agg(*[F.struct(F.avg(F.col(c).cast("double")).alias("m"), F.stddev_pop(F.col(c).cast("double")).alias("s")).alias(f"_{c}") for c in numeric])
    z = lambda c: F.when(F.col(f"_{c}.s") > 0, (F.col(c).cast("double") - F.col(f"_{c}.m")) / F.col(f"_{c}.s")).otherwise(F.lit(0.0))
    guess = F.array(*[F.struct((-F.abs(z(c))).alias("k"), F.lit(c.replace("_", " ")).alias("feature"), F.signum(z(c)).cast("int").alias("direction")) for c in numeric])
    rows = df.crossJoin(F.broadcast(stats)).withColumn("guess", F.slice(F.array_sort(guess), 1, n)).drop(*[f"_{c}" for c in numeric])
    clause = lambda g: F.concat(F.lit("The "), g["feature"], F.when(g["direction"] < 0, " lowers").otherwise(" raises"), F.lit(" the estimate."))
    return rows.withColumn("text", F.array_join(F.transform("guess", clause), " "))
