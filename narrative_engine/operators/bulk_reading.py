"""Narratives read by the million: the rules of :mod:`claims` and the measures of style, in batches.

:func:`claims.claims` looks for about ninety phrases in every text, one pass of the text each, as an
expression that is interpreted row by row.  Here a batch is read as Arrow columns; the answers are
the same, field by field.  A clause that comes again is taken apart once for as long as it is kept.
"""

from __future__ import annotations

import functools
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from narrative_engine.operators.claims import ABSENT, CONTRAST, DOWN, GREATER, GREATER_BEFORE, LIST_MARKS, NONE_VALUES, NUMBER_TOKEN, ROUNDED, SMALLER, SMALLER_BEFORE, UP, Reading, spaced
from narrative_engine.shipping import ship

BLANK = r" \t\n\x0b\f\r"  # what \s is to the JVM
THOUSANDS = re.compile(r"([0-9]),([0-9]{3})")
OTHER = re.compile(rf"[^\w.,;!?%{BLANK}-]")
STOP = re.compile(rf"[.;!?]+(?:[{BLANK}]|\Z)")
BLANKS = re.compile(rf"[{BLANK}]+")
NUMBER = re.compile(r"[0-9]+(?:\.[0-9]+)?")
WORD = re.compile(r"[^ \t\n\r]+")
CLAUSE_END = re.compile(rf"[.;!?](?:[{BLANK}]|\Z|(?=[\x85\u2028\u2029]\Z))|, while |, but ")
WORD_CODES = {w: code for phrases, code in ((ABSENT, "@n@"), (DOWN, "@d@"), (UP, "@u@")) for w in phrases if " " not in w}
IS_NUMBER = re.compile(NUMBER_TOKEN)
#: Clauses, names and values that a reader keeps apart from the rows.
KEPT = 1 << 15

CLAIMS = "struct<found:array<struct<feature:string,mentioned:boolean,value:boolean,contribution:boolean,value_state:string,contrib_state:string,direction:int,wrong:boolean>>,invented:boolean>"


def _by_length(phrases: tuple[str, ...]) -> list[str]:
    return [spaced(p) for p in sorted(phrases, key=lambda p: (-len(p), p))]


class Reader:
    """Reads texts as ``reading`` says."""

    def __init__(self, reading: Reading) -> None:
        self.reading = reading
        several = lambda phrases: tuple(p for p in phrases if " " in p)
        steps = [(_by_length(GREATER), " @g@ "), (_by_length(SMALLER), " @s@ "), (_by_length(reading.up), " @u@ "), (_by_length(reading.down), " @d@ "), (_by_length(several(UP)), " @u@ "), (_by_length(several(DOWN)), " @d@ "), (_by_length(several(ABSENT)), " @n@ ")]
        before = [(f" {w}  @", f" {code}  @") for words, code in ((GREATER_BEFORE, "@g@"), (SMALLER_BEFORE, "@s@")) for w in words]
        self.phrases = before + [(p, code) for phrases, code in steps for p in phrases]
        self.items_of = functools.lru_cache(KEPT)(self._items_of)
        self.name_of = functools.lru_cache(KEPT)(self._name_of)
        self.literal_of = functools.lru_cache(KEPT)(self._literal_of)

    @staticmethod
    def _name_of(name: str) -> str:
        return " " + BLANKS.sub("  ", name.lower().strip(" ")) + " "

    @staticmethod
    def _literal_of(value: str) -> tuple[str, bool]:
        low = value.lower()
        return " " + BLANKS.sub("  ", OTHER.sub(" ", low).replace(",", " , ").strip(" ")) + " ", low in NONE_VALUES

    def _items_of(self, clause: str) -> list[tuple[int, str, bool, int, float | None]]:
        """(at, tok, by, part, number) of the codes and numbers of a clause."""
        for phrase, code in self.phrases:
            clause = clause.replace(phrase, code)
        out, at, part, last = [], 0, 0, ""
        for t in clause.split():
            if t in ROUNDED:
                continue
            t = WORD_CODES.get(t, t)
            if t[0] == "@":
                out.append((at, t, last == "by", part, None))
            elif IS_NUMBER.match(t):
                out.append((at, t, last == "by", part, abs(float(t.replace("%", "")))))
            if t in LIST_MARKS:
                part += 1
            last, at = t, at + 1
        return out

    def tokens(self, text: str) -> str:
        t = text.lower()
        for mark in "$€£|":
            t = t.replace(mark, "")
        if "," in t:
            t = THOUSANDS.sub(r"\1\2", THOUSANDS.sub(r"\1\2", t))
        t = STOP.sub(" | ", OTHER.sub(" ", t).replace(",", " , "))
        return " " + "  ".join(["|" if w in CONTRAST else w for w in t.split()]) + " "

    def named(self, t: str, features: list[str]) -> str:
        entries = [(0, name, f" @{k}@ ") for k, f in enumerate(features) for name in (f, *self.reading.aliases.get(f, ()))]
        entries += [(1, name, " @x@ ") for name in self.reading.others]
        for _, _, name, code in sorted((-len(name), own, self.name_of(name), code) for own, name, code in entries):
            t = t.replace(name, code)
        return t

    def read(self, text: str, expl: list[tuple[str, str | None, float | None, float | None, float | None]]) -> tuple[list[tuple], bool]:
        """Records and whether something is invented; ``expl`` has (feature, value, value_num, contribution, number)."""
        tolerance = self.reading.tolerance
        near = lambda n, v: v is not None and abs(n - abs(v)) <= abs(v) * tolerance + 1e-9
        clauses = self.named(self.tokens(text), [x[0] for x in expl]).split("|")
        items = [(ci, *item) for ci, clause in enumerate(clauses) for item in self.items_of(clause)]
        features = [m for m in items if m[2][0] == "@" and m[2][1:2] not in ("u", "d", "g", "s", "n", "x")]
        numbers = {}
        for ci, at, _, by, part, number in items:
            if number is not None:
                owner = min(((0 if m[4] == part else 1 if m[1] < at else 2, abs(m[1] - at), m[1], m[2]) for m in features if m[0] == ci), default=None)
                numbers.setdefault(owner and owner[3], []).append((number, by))
        loose = any(not any(near(n, x[4]) or near(n, x[3]) for x in expl) for n, _ in numbers.get(None, ()))
        foreign = any(
            o[2] == "@x@" and not any(m[0] == o[0] for m in features) and any(c[0] == o[0] and (c[2] in ("@u@", "@d@") or c[5] is not None) for c in items) for o in items
        ) if self.reading.others else False
        return [self._record(x, f"@{k}@", items, numbers.get(f"@{k}@", ()), clauses, near) for k, x in enumerate(expl)], loose or foreign

    def _record(self, x: tuple, own: str, items: list[tuple], numbers: list[tuple[float, bool]], clauses: list[str], near) -> tuple:
        feature, value, value_num, contribution, number = x
        mine = [m for m in items if m[2] == own]
        told_value = exact_value = told_contrib = exact_contrib = wrong_number = False
        for n, by in numbers:
            is_value, is_contrib = near(n, number), near(n, contribution)
            if not (by and is_contrib):
                told_value = told_value or is_value
                exact_value = exact_value or (number is not None and n == abs(number))
            if by or not is_value:
                told_contrib = told_contrib or is_contrib
                exact_contrib = exact_contrib or (contribution is not None and n == abs(contribution))
            wrong_number = wrong_number or not (is_value or is_contrib)
        literal, is_none = self.literal_of(value) if value is not None else (None, False)
        spoken = literal is not None and any(literal in clauses[m[0]] for m in mine)
        compared, absent_near, absent_before, ways = None, False, False, []
        for ci, at, *_ in mine:
            after = before = None
            for cue in items:
                if cue[0] != ci:
                    continue
                if cue[2] == "@u@" or cue[2] == "@d@":
                    if cue[1] > at:
                        after = after or cue[2]
                    elif cue[1] < at:
                        before = cue[2]
                elif cue[2] == "@n@":
                    absent_near = absent_near or abs(cue[1] - at) <= 4
                    absent_before = absent_before or 1 <= at - cue[1] <= 2
                elif compared is None and (cue[2] == "@g@" or cue[2] == "@s@") and (cue[1] > at or cue[1] == at - 1):
                    compared = cue[2]
            if after or before:
                ways.append(1 if (after or before) == "@u@" else -1)
        categorical = value_num is None
        zero = value_num == 0 and absent_near
        said = (spoken or told_value or (is_none and absent_near)) if categorical else (told_value or zero)
        yes = is_none and any(" yes " in clauses[m[0]] for m in mine)
        wrong_value = categorical and value is not None and ((not is_none and absent_before and not spoken) or yes)
        exact = said if categorical else (exact_value or zero)
        sign = -1 if contribution is not None and contribution < 0 else 1
        return (
            feature, bool(mine), said, told_contrib,
            "wrong" if wrong_value else "exact" if exact else "approx" if said else "comparative" if compared else "absent",
            "exact" if exact_contrib else "approx" if told_contrib else "wrong" if wrong_number else "absent",
            (1 if all(w == sign for w in ways) else -1) if ways else 0, wrong_number or wrong_value,
        )


def surface(text: str) -> list[int]:
    """The surface terms of :func:`grading.style_vector`."""
    n = max(len(WORD.findall(text)), 1)
    rate = lambda s: text.count(s) * 100 // n
    return [
        rate(","), rate("("), rate(";"), rate("about"), rate("We ") + rate("our "), rate("!"), rate("0"), rate("which"), rate("feature"),
        n // max(len(CLAUSE_END.findall(text)), 1), (len(text) - n) * 2 // n,
    ]


def shown(text: str, expl: list[tuple], mask_topic: bool) -> str:
    """The text that style is measured on, as :func:`grading.masked` has it."""
    if not mask_topic:
        return text
    for feature, value, *_ in expl[:3]:
        for topic, mark in ((value, "y"), (feature, "x")):
            text = text.replace(topic, mark) if topic else text
    return NUMBER.sub("0", text)


def _claims(read: list[tuple[list[tuple], bool]], kind: pa.StructType) -> pa.StructArray:
    records = [r for found, _ in read for r in found]
    ends = [0]
    for found, _ in read:
        ends.append(ends[-1] + len(found))
    one = kind.field("found").type.value_type
    fields = list(zip(*records)) or [()] * len(one)
    rows = pa.StructArray.from_arrays([pa.array(c, one.field(i).type) for i, c in enumerate(fields)], fields=list(one))
    found = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), rows, type=kind.field("found").type)
    return pa.StructArray.from_arrays([found, pa.array([i for _, i in read], pa.bool_())], fields=list(kind))


def measured(df: DataFrame, reading: Reading, mask_topic: bool) -> DataFrame:
    """``df`` (style, expl, text) with ``claims``, ``_v`` (its surface terms) and ``n_words``."""
    spark = df.sparkSession
    ship(spark)
    # what a value is as a number is left to the JVM's own reading
    rows = df.withColumn("_numbers", F.transform("expl", lambda x: F.coalesce(x["value_num"], x["value"].try_cast("double"))))
    out = df.select("*", F.lit(None).cast(CLAIMS).alias("claims"), F.lit(None).cast("array<int>").alias("_v"), F.lit(None).cast("int").alias("n_words")).schema
    out = StructType.fromJson(out.jsonValue())
    names = df.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark.sql.pandas.types import to_arrow_type

        reader, kind = Reader(reading), to_arrow_type(out["claims"].dataType)
        for b in batches:
            lists = b.column(names.index("expl"))
            of = lambda name: lists.flatten().field(name).to_pylist()
            flat = list(zip(of("feature"), of("value"), of("value_num"), of("contribution"), b.column(len(names)).flatten().to_pylist()))
            sizes, at, read, styles, words = lists.value_lengths().to_pylist(), 0, [], [], []
            for text, size in zip(b.column(names.index("text")).to_pylist(), sizes):
                expl = flat[at : at + (size or 0)]
                at += size or 0
                read.append(reader.read(text, expl))
                styles.append(surface(shown(text, expl, mask_topic)))
                words.append(len(WORD.findall(text)))
            yield pa.RecordBatch.from_arrays([*b.columns[: len(names)], _claims(read, kind), pa.array(styles, pa.list_(pa.int32())), pa.array(words, pa.int32())], names=out.names)

    return rows.mapInArrow(run, out)
