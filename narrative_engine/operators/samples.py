"""From samples of a style, pairs of an explanation and its narrative, to exemplars the writer can follow.

A narrative is read once: every feature, value, contribution and direction that it tells becomes a
slot, what stands before the first feature is the lead, what parts the features the joiner, what
follows the last the tail.  What a sample leaves out or rounds stays left out or rounded wherever
its slots are filled again, so a style's habits travel and so do its flaws.  Samples are a handful
per style, read on the driver.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from narrative_engine.settings import TOLERANCE

#: Phrases that tell a direction, rising and falling.
CUE_PAIRS = (
    ("more likely", "less likely"), ("raises", "lowers"), ("raise", "lower"), ("raised", "lowered"), ("raising", "lowering"), ("increases", "decreases"), ("increase", "decrease"),
    ("increased", "decreased"), ("increasing", "decreasing"), ("adds to", "takes from"), ("added to", "took from"), ("boosts", "cuts"), ("boosted", "cut"), ("pushes up", "pushes down"),
    ("pushed up", "pushed down"), ("drives up", "drives down"), ("drove up", "drove down"), ("higher", "lower"), ("increases", "reduces"), ("increased", "reduced"),
)
JOINERS = re.compile(r"(?:[.;!?]|,)\s+(?:while|whereas|but|and)\s+|;\s+|[.!?]\s+(?=[A-Z])|,\s+|\s+and\s+")
ARTICLE = re.compile(r"\s+(?:the|its|their|a|an|this|that|our|his|her)\b", re.I)
NUMBER = re.compile(r"-?[0-9](?:[0-9,]*[0-9])?(?:\.[0-9]+)?")


@dataclass(frozen=True)
class Clause:
    """Slot text of one feature and the phrases for its two directions."""

    slots: str
    up: str
    down: str


@dataclass(frozen=True)
class Exemplar:
    """A sample with its slots; ``omits``: it tells fewer features than its explanation has."""

    ex: str
    expl_text: str
    text: str
    lead: str
    joiner: str
    tail: str
    omits: bool
    clauses: tuple[Clause, ...]


def triples(expl_text: str) -> list[tuple[str, str, float]]:
    """(feature, value, contribution) of a parenthesised list, or of one bare triple."""
    text = expl_text.strip()
    bodies = re.findall(r"\(((?:[^()]|\([^()]*\))*)\)", text) if text.startswith("(") else [text]
    out = []
    for body in bodies:
        m = re.fullmatch(r"(.*),([^,]*),([^,]*)", body.strip(), re.S)
        if m is None:
            raise ValueError(f"not a (feature, value, contribution): {body!r}")
        out.append((m[1].strip(), m[2].strip(), float(m[3])))
    return out


def _word(phrase: str) -> re.Pattern:
    return re.compile(rf"(?<![\w]){re.escape(phrase)}(?![\w])", re.I)


def _number(text: str) -> float:
    return abs(float(text.replace(",", "")))


def _near(x: float, y: float) -> bool:
    return abs(x - abs(y)) <= abs(y) * TOLERANCE + 1e-9


def _cue(text: str) -> tuple[int, int, str, str] | None:
    """The first telling phrase of ``text``, the longest of those that start there."""
    best = None
    for up, down in CUE_PAIRS:
        for phrase in (up, down):
            m = _word(phrase).search(text)
            if m and phrase == "lower" and (up == "raise") != bool(ARTICLE.match(text, m.end())):
                continue  # a verb before an article, else an adjective
            if m and (best is None or (m.start(), -len(phrase)) < (best[0], best[0] - best[1])):
                best = (m.start(), m.end(), up, down)
    return best


def _slotted(text: str, feature: str, value: str, contribution: float) -> Clause:
    """``text`` of one feature with its slots."""
    spans: list[tuple[int, int, str]] = []
    name = _word(feature).search(text)
    spans.append((name.start(), name.end(), "{f}"))
    free = lambda a, b: all(b <= s or a >= e for s, e, _ in spans)
    try:
        amount = abs(float(value.replace(",", "")))
    except ValueError:
        amount = None
    literal = next((m for m in _word(value).finditer(text) if free(m.start(), m.end())), None) if value else None
    if literal:
        spans.append((literal.start(), literal.end(), "{v}"))
    for m in NUMBER.finditer(text):
        if not free(m.start(), m.end()):
            continue
        x = _number(m[0])
        if not literal and amount is not None and _near(x, amount) and not text[: m.start()].rstrip().endswith("by"):
            literal = m
            spans.append((m.start(), m.end(), "{v}"))
        elif f"{x:.2f}" == f"{abs(contribution):.2f}" and "." in m[0]:
            spans.append((m.start(), m.end(), "{c}"))
        elif _near(x, contribution):
            spans.append((m.start(), m.end(), "{t}" if "," in m[0] and abs(x - abs(contribution)) < 0.5 else "{r}"))
        else:
            spans.append((m.start(), m.end(), "{k}"))
    rest = list(text)
    for a, b, _ in spans:
        rest[a:b] = "\x00" * (b - a)
    cue = _cue("".join(rest))
    up, down = ("", "")
    if cue:
        spans.append((cue[0], cue[1], "{d}"))
        up, down = cue[2], cue[3]
    out, at = "", 0
    for a, b, slot in sorted(spans):
        out, at = out + text[at:a] + slot, b
    return Clause(out + text[at:], up, down)


def derived(ex: str, expl_text: str, narrative: str) -> Exemplar:
    """The exemplar that a sample makes; features it never names are its omissions."""
    found = triples(expl_text)
    masked, spots = narrative, []
    for feature, value, contribution in sorted(found, key=lambda t: -len(t[0])):  # so that no name is found inside a longer one
        m = _word(feature).search(masked)
        if m:
            spots.append((m.start(), m.end(), feature, value, contribution))
            masked = masked[: m.start()] + "\x00" * (m.end() - m.start()) + masked[m.end() :]
    if not spots:
        raise ValueError("the narrative names no feature of its explanation")
    spots.sort()
    # a clause starts after the last joiner before its feature's name, and the joiner must follow the feature before
    starts, joins = [], []
    for k, (a, *_rest) in enumerate(spots):
        low = spots[k - 1][1] if k else 0
        cuts = [m for m in JOINERS.finditer(narrative, low, a) if m.end() <= a]
        strong = [m for m in cuts if not re.fullmatch(r",\s+|\s+and\s+", m[0])] or ([m for m in cuts if m[0].strip()] or cuts)
        cut = strong[-1] if strong else None
        if k == 0:
            colon = narrative.rfind(": ", 0, a)
            starts.append(max(cut.end() if cut else 0, colon + 2 if colon >= 0 else 0))
        else:
            joins.append(cut)
            starts.append(cut.end() if cut else a)
    lead = narrative[: starts[0]]
    joiner = joins[0][0] if joins and joins[0] else "; "
    ends = [joins[k].start() if joins[k] else starts[k + 1] for k in range(len(joins))]
    last = narrative[starts[-1] :]
    stop = re.search(r",\s+(?:as|so|which is why|because)\s", last)
    mark = re.search(r"[.!?](?=\s+[A-Z]|\s*$)", last)
    until = min(x.start() for x in (stop, mark) if x) if stop or mark else len(last)
    ends.append(starts[-1] + until)
    clauses = tuple(_slotted(narrative[a:b], f, v, c) for a, b, (_, _, f, v, c) in zip(starts, ends, spots))
    return Exemplar(ex, expl_text, narrative, lead, joiner, narrative[ends[-1] :], len(clauses) < len(found), clauses)


def as_row(e: Exemplar) -> tuple:
    return (e.ex, e.expl_text, e.text, e.lead, e.joiner, e.tail, e.omits, [(c.slots, c.up, c.down) for c in e.clauses])
