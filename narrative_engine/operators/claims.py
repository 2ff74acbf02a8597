"""What a narrative claims of each feature of its explanation, read from plain prose.

The text is brought to tokens that blanks part.  Feature names (and aliases), longest first, are
replaced by codes, so ``interest rate`` is never read as ``rate``; so are the phrases that tell a
direction, a comparison or an absence.  Within a clause every number belongs to the nearest feature
of its list item, or else to the last one before it; a feature's direction is the next one told after
it, or else the last one before it.  Everything
is a column expression over the row; nothing is exploded.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

from narrative_engine.operators.columns import let
from narrative_engine.settings import TOLERANCE

#: Phrases that tell a direction, a comparison, an absence, or that a number is rounded.
UP = (
    "more likely", "raises", "raise", "raised", "raising", "increases", "increase", "increased", "increasing", "higher", "adds to", "added to", "boosts", "boosted",
    "pushes up", "pushed up", "drives up", "drove up",
)
DOWN = (
    "less likely", "lowers", "lower", "lowered", "lowering", "decreases", "decrease", "decreased", "decreasing", "reduces", "reduce", "reduced", "reducing", "takes from", "took from",
    "cuts", "pushes down", "pushed down", "drives down", "drove down", "drops", "dropped",
)
GREATER = ("larger than usual", "greater than usual", "higher than usual", "longer than usual", "more than usual", "above average", "above the average")
SMALLER = ("smaller than usual", "lower than usual", "shorter than usual", "fewer than usual", "less than usual", "below average", "below the average")
GREATER_BEFORE = ("larger", "bigger", "greater", "higher", "longer")
SMALLER_BEFORE = ("smaller", "lower", "shorter", "fewer")
ABSENT = ("lack of any", "lack of the", "lack of a", "lack of", "absence of any", "absence of the", "absence of a", "absence of", "without any", "without the", "without a", "without", "no")
ROUNDED = ("about", "around", "roughly", "approximately", "nearly", "almost", "some")
CONTRAST = ("while", "whereas", "but")
#: Values that an absence expresses.
NONE_VALUES = ("no", "none", "0", "false", "absent")
#: What is no part of a word, but for the ends of clauses and commas.
OTHER_MARKS = r"[^\p{L}\p{N}_.,;!?%\s-]"
#: Tokens that part the items of a list.
LIST_MARKS = (",", "and")
#: Codes that are no feature's of the explanation.
CODES = ("@u@", "@d@", "@g@", "@s@", "@n@", "@x@")
NUMBER_TOKEN = r"^-?[0-9]+(\.[0-9]+)?%?$"


@dataclass(frozen=True)
class Reading:
    """How a text is read: phrases of the domain that turn a direction round, aliases of features, features that it has besides."""

    tolerance: float = TOLERANCE
    up: tuple[str, ...] = ("less likely to fail",)
    down: tuple[str, ...] = ("more likely to fail",)
    aliases: dict[str, tuple[str, ...]] = field(default_factory=dict)
    others: tuple[str, ...] = ()


def spaced(phrase: str) -> str:
    return " " + "  ".join(phrase.split()) + " "


def tokens_of(text: Column) -> Column:
    """Lower-case tokens, each with a blank of its own on both sides; clauses end with ``|``."""
    t = F.regexp_replace(F.lower(text), "[$€£|]", "")
    for _ in range(2):  # marks of thousands
        t = F.regexp_replace(t, "([0-9]),([0-9]{3})", "$1$2")
    t = F.replace(F.regexp_replace(t, OTHER_MARKS, " "), F.lit(","), F.lit(" , "))
    t = F.regexp_replace(t, r"[.;!?]+(\s|$)", " | ")
    t = F.concat(F.lit(" "), F.trim(F.regexp_replace(t, r"\s+", "  ")), F.lit(" "))
    for word in CONTRAST:
        t = F.replace(t, F.lit(spaced(word)), F.lit(" | "))
    return t


def _replaced(t: Column, phrases: tuple[str, ...], code: str) -> Column:
    for phrase in sorted(phrases, key=lambda p: (-len(p), p)):
        t = F.replace(t, F.lit(spaced(phrase)), F.lit(code))
    return t


def named(t: Column, expl: Column, reading: Reading) -> Column:
    """Feature names by ``@k@``, ``k`` its place in ``expl``, and names of other features by ``@x@``; longer names first."""
    aliases = F.create_map(*[F.lit(v) if isinstance(v, str) else F.array(*map(F.lit, v)) for kv in reading.aliases.items() for v in kv]) if reading.aliases else None
    entry = lambda name, code, own: F.struct((-F.length(name)).alias("long"), own.alias("own"), F.concat(F.lit(" "), F.regexp_replace(F.trim(F.lower(name)), r"\s+", "  "), F.lit(" ")).alias("name"), code.alias("code"))
    names = lambda x: F.array(x["feature"]) if aliases is None else F.concat(F.array(x["feature"]), F.coalesce(aliases[x["feature"]], F.array().cast("array<string>")))
    known = F.flatten(F.transform(expl, lambda x, k: F.transform(names(x), lambda name: entry(name, F.concat(F.lit(" @"), k.cast("string"), F.lit("@ ")), F.lit(0)))))
    if reading.others:
        known = F.concat(known, F.array(*[entry(F.lit(o), F.lit(" @x@ "), F.lit(1)) for o in reading.others]))
    return F.aggregate(F.array_sort(known), t, lambda acc, e: F.replace(acc, e["name"], e["code"]))


def _of(phrases: tuple[str, ...], words: bool) -> tuple[str, ...]:
    """Those of a single word, or the others."""
    return tuple(p for p in phrases if (" " not in p) == words)


def coded(t: Column, reading: Reading) -> Column:
    """Phrases by codes: ``@u@`` and ``@d@`` directions, ``@g@`` and ``@s@`` comparisons, ``@n@`` absence.

    Single words are left to :func:`_tokens`, which looks each token up; none of them is in a phrase that comes after it.
    """
    for word in GREATER_BEFORE:
        t = F.replace(t, F.lit(f" {word}  @"), F.lit(" @g@  @"))
    for word in SMALLER_BEFORE:
        t = F.replace(t, F.lit(f" {word}  @"), F.lit(" @s@  @"))
    t = _replaced(_replaced(t, GREATER, " @g@ "), SMALLER, " @s@ ")
    t = _replaced(_replaced(t, reading.up, " @u@ "), reading.down, " @d@ ")
    t = _replaced(_replaced(t, _of(UP, False), " @u@ "), _of(DOWN, False), " @d@ ")
    return _replaced(t, _of(ABSENT, False), " @n@ ")


def _tokens(c: Column) -> Column:
    """The tokens of a clause, single words by their codes."""
    ts = F.filter(F.split(F.trim(c), " +"), lambda t: ~t.isin(*ROUNDED))
    return F.transform(ts, lambda t: F.when(t.isin(*_of(UP, True)), "@u@").when(t.isin(*_of(DOWN, True)), "@d@").when(t.isin(*_of(ABSENT, True)), "@n@").otherwise(t))


def _items(clauses: Column) -> Column:
    """(ci, at, tok, by, part) of the codes and numbers, in order; ``part`` numbers the items of a list within the clause."""
    def of_clause(c: Column, ci: Column) -> Column:
        def listed(ts: Column) -> Column:
            places = F.sequence(F.lit(0), F.size(ts) - 1)  # of no tokens 0 and -1, where get finds nothing
            told = F.filter(places, lambda i: F.get(ts, i).startswith("@") | F.get(ts, i).rlike(NUMBER_TOKEN))
            item = lambda i, marks: F.struct(
                ci.alias("ci"), i.alias("at"), F.get(ts, i).alias("tok"), F.coalesce(F.get(ts, i - 1) == "by", F.lit(False)).alias("by"), F.size(F.filter(marks, lambda m: m < i)).alias("part")
            )
            return let(F.filter(places, lambda i: F.get(ts, i).isin(*LIST_MARKS)), lambda marks: F.transform(told, lambda i: item(i, marks)))

        return let(_tokens(c), listed)

    return F.flatten(F.transform(clauses, of_clause))


def _is_feature(x: Column) -> Column:
    return x["tok"].startswith("@") & ~x["tok"].isin(*CODES)


def _numbers(items: Column, features: Column) -> Column:
    """(num, by, owner) of the numbers; the owner is the nearest of ``features`` of the list item, else the last one before, else the next of the clause."""
    def owner(n: Column) -> Column:
        near = F.filter(features, lambda m: m["ci"] == n["ci"])
        kind = lambda m: F.when(m["part"] == n["part"], 0).when(m["at"] < n["at"], 1).otherwise(2)
        return F.array_min(F.transform(near, lambda m: F.struct(kind(m).alias("kind"), F.abs(m["at"] - n["at"]).alias("far"), m["at"].alias("at"), m["tok"].alias("tok"))))["tok"]

    numbers = F.filter(items, lambda x: ~x["tok"].startswith("@"))
    return F.transform(numbers, lambda n: F.struct(F.abs(F.replace(n["tok"], F.lit("%"), F.lit("")).cast("double")).alias("num"), n["by"].alias("by"), owner(n).alias("owner")))


def _way(m: Column, items: Column) -> Column:
    def said(cues: Column) -> Column:
        after = F.get(F.filter(cues, lambda c: c["at"] > m["at"]), F.lit(0))["tok"]
        before = F.try_element_at(F.filter(cues, lambda c: c["at"] < m["at"]), F.lit(-1))["tok"]
        return F.coalesce(after, before)

    cues = F.filter(items, lambda c: (c["ci"] == m["ci"]) & c["tok"].isin("@u@", "@d@"))
    return let(let(cues, said), lambda s: F.when(s == "@u@", 1).when(s == "@d@", -1).otherwise(0))


def claims(text: Column, expl: Column, reading: Reading = Reading(), means: Column | None = None) -> Column:
    """Struct ``found`` (a record per feature) and ``invented`` (a number or feature that the explanation doesn't have).

    A record: feature, mentioned, value and contribution (told, within the tolerance), value_state
    (absent, exact, approx, comparative, wrong), contrib_state, direction (1 right, -1 wrong, 0 untold)
    and wrong.  ``means`` (map feature -> usual value) lets comparisons be checked.
    """
    near = lambda n, v: F.abs(n - F.abs(v)) <= F.abs(v) * reading.tolerance + 1e-9
    no = lambda c: F.coalesce(c, F.lit(False))

    def of_number(x: Column, n: Column, number: Column) -> Column:
        contrib = no(near(n["num"], x["contribution"]))
        return F.struct(
            no(near(n["num"], number)).alias("value"), contrib.alias("contrib"), no(n["num"] == F.abs(number)).alias("exact_value"), no(n["num"] == F.abs(x["contribution"])).alias("exact_contrib"), n["by"].alias("by")
        )

    def told_numbers(nums: Column) -> Column:
        as_value, as_contrib = lambda n: ~(n["by"] & n["contrib"]), lambda n: n["by"] | ~n["value"]
        return F.struct(
            F.exists(nums, lambda n: n["value"] & as_value(n)).alias("value"), F.exists(nums, lambda n: n["exact_value"] & as_value(n)).alias("exact_value"),
            F.exists(nums, lambda n: n["contrib"] & as_contrib(n)).alias("contrib"), F.exists(nums, lambda n: n["exact_contrib"] & as_contrib(n)).alias("exact_contrib"),
            F.exists(nums, lambda n: ~(n["value"] | n["contrib"])).alias("wrong"),
        )

    def told_words(x: Column, mine: Column, items: Column, clauses: Column) -> Column:
        low = F.lower(x["value"])
        literal = F.concat(F.lit(" "), F.regexp_replace(F.trim(F.regexp_replace(F.regexp_replace(low, OTHER_MARKS, " "), ",", " , ")), r"\s+", "  "), F.lit(" "))
        spoken = let(literal, lambda words: F.exists(mine, lambda m: F.contains(F.get(clauses, m["ci"]), words)))
        absent = lambda nearby: F.exists(items, lambda n: (n["tok"] == "@n@") & F.exists(mine, lambda m: (n["ci"] == m["ci"]) & nearby(m, n)))
        compared = F.get(F.flatten(F.transform(mine, lambda m: F.filter(items, lambda c: (c["ci"] == m["ci"]) & c["tok"].isin("@g@", "@s@") & ((c["at"] > m["at"]) | (c["at"] == m["at"] - 1))))), F.lit(0))["tok"]
        return F.struct(
            spoken.alias("spoken"), low.isin(*NONE_VALUES).alias("is_none"), absent(lambda m, n: F.abs(n["at"] - m["at"]) <= 4).alias("absent_near"),
            absent(lambda m, n: (m["at"] - n["at"]).between(1, 2)).alias("absent_before"), F.exists(mine, lambda m: F.contains(F.get(clauses, m["ci"]), F.lit(" yes "))).alias("yes"), compared.alias("compared"),
        )

    def told_value(x: Column, num: Column, word: Column) -> Column:
        categorical = x["value_num"].isNull()
        zero = no(x["value_num"] == 0) & word["absent_near"]
        value = F.when(categorical, word["spoken"] | num["value"] | (word["is_none"] & word["absent_near"])).otherwise(num["value"] | zero)
        wrong_value = categorical & ((~word["is_none"] & word["absent_before"] & ~word["spoken"]) | (word["is_none"] & word["yes"]))
        usual = means[x["feature"]].cast("double") if means is not None else F.lit(None).cast("double")
        wrong_compared = no(((word["compared"] == "@g@") & (x["value_num"] < usual)) | ((word["compared"] == "@s@") & (x["value_num"] > usual)))
        return F.struct(value.alias("told"), F.when(~categorical, num["exact_value"] | zero).alias("exact"), no(wrong_value).alias("wrong"), wrong_compared.alias("wrong_compared"))

    def record(x: Column, own: Column, items: Column, numbers: Column, clauses: Column) -> Column:
        def of(mine: Column, num: Column, word: Column, value: Column) -> Column:
            sign = F.when(x["contribution"] < 0, -1).otherwise(1)
            ways = F.filter(F.transform(mine, lambda m: _way(m, items)), lambda w: w != 0)
            direction = let(ways, lambda ws: F.when(F.size(ws) == 0, 0).when(F.forall(ws, lambda w: w == sign), 1).otherwise(-1))
            exact = F.when(x["value_num"].isNull(), value["told"]).otherwise(value["exact"])
            return F.struct(
                x["feature"].alias("feature"), (F.size(mine) > 0).alias("mentioned"), no(value["told"]).alias("value"), no(num["contrib"]).alias("contribution"),
                F.when(value["wrong"] | value["wrong_compared"], "wrong").when(no(exact), "exact").when(no(value["told"]), "approx").when(word["compared"].isNotNull(), "comparative").otherwise("absent").alias("value_state"),
                F.when(num["exact_contrib"], "exact").when(num["contrib"], "approx").when(num["wrong"], "wrong").otherwise("absent").alias("contrib_state"),
                direction.cast("int").alias("direction"), (num["wrong"] | value["wrong"] | value["wrong_compared"]).alias("wrong"),
            )

        number = F.coalesce(x["value_num"], x["value"].try_cast("double"))
        nums = let(number, lambda known: F.transform(F.filter(numbers, lambda n: n["owner"] == own), lambda n: of_number(x, n, known)))
        return let(
            F.filter(items, lambda m: m["tok"] == own),
            lambda mine: let(let(nums, told_numbers), lambda num: let(told_words(x, mine, items, clauses), lambda word: let(told_value(x, num, word), lambda value: of(mine, num, word, value)))),
        )

    def judged(items: Column, clauses: Column) -> Column:
        def with_numbers(numbers: Column) -> Column:
            found = F.transform(expl, lambda x, k: let(F.concat(F.lit("@"), k.cast("string"), F.lit("@")), lambda own: record(x, own, items, numbers, clauses)))
            of_expl = lambda n: F.exists(expl, lambda x: no(near(n["num"], F.coalesce(x["value_num"], x["value"].try_cast("double")))) | no(near(n["num"], x["contribution"])))
            loose = F.exists(numbers, lambda n: n["owner"].isNull() & ~of_expl(n))
            same = lambda a, b: a["ci"] == b["ci"]
            foreign = F.exists(items, lambda o: (o["tok"] == "@x@") & ~F.exists(items, lambda m: same(m, o) & _is_feature(m)) & F.exists(items, lambda c: same(c, o) & (c["tok"].isin("@u@", "@d@") | ~c["tok"].startswith("@"))))
            return F.struct(found.alias("found"), (loose | foreign).alias("invented"))

        return let(let(F.filter(items, _is_feature), lambda features: _numbers(items, features)), with_numbers)

    def read(t: Column) -> Column:
        return let(F.split(t, r"\|"), lambda clauses: let(_items(F.split(coded(t, reading), r"\|")), lambda items: judged(items, clauses)))

    return let(named(tokens_of(text), expl, reading), read)
