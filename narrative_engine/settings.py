"""Fixed dimensions of the engine: metrics, techniques, base prompts, domains, phrases, styles."""

from __future__ import annotations

from dataclasses import dataclass

# What the published experiment used.
WEIGHTS = {"a": 4.0, "c": 2.0, "f": 1.0, "s": 1.0}
TOP_GRADE = {"a": 1.0, "c": 2.0, "f": 4.0, "s": 4.0}
DRAWS, NEED_EQUAL = 5, 4
DEFAULT_EXEMPLARS = 5
LONGEST_SHARE = 0.9
GATE = {"a": 1.0, "c": 2.0, "f": 4.0, "s": 3.5}
BANDS = (("low", float("-inf"), 3.0), ("middle", 3.0, 3.5), ("high", 3.5, float("inf")))
#: (technique, base prompt, hand-written exemplars, bootstrapped exemplars)
TECHNIQUES = (
    (1, "plain", 0, 0), (2, "lay", 0, 0), (3, "exhaustive", 0, 0),
    (4, "plain", 1, 0), (5, "plain", 3, 0), (6, "plain", 5, 0),
    (7, "plain", 1, 1), (8, "plain", 1, 3), (9, "plain", 3, 1), (10, "plain", 3, 3),
    (11, "plain", 5, 1), (12, "plain", 5, 3), (13, "plain", 5, 5),
)
TOLERANCE = 0.05

#: Our own wordings of a neutral, a lay-reader and a name-every-value instruction.
BASE_PROMPTS = {
    "plain": "Turn the explanation of a model's prediction below into prose a person can read, using the format and the context given with it.",
    "lay": "Your readers know nothing of machine learning. Turn the explanation of a model's prediction below into prose they can follow, "
    "using the format and the context given with it. Sound like a person speaking naturally.",
    "exhaustive": "Turn the explanation of a model's prediction below into prose a person can read, using the format and the context given "
    "with it. State each value of the explanation in the text.",
}
OUTPUT_RULES = "Answer with the prose alone, without lists or headings."
CUE = "Prose:"

FORMATS = {
    "contributions": "A list of (feature, value, contribution), largest contribution first; the sign tells whether the feature raised or lowered the output.",
    "contributions_with_statistics": "A list of (feature, value, contribution, usual value), largest contribution first; the sign tells the direction.",
    "rules": "A list of (condition, outcome), in order of importance.",
    "examples": "A list of (case, outcome): cases like this one and how they came out.",
}


@dataclass(frozen=True)
class Domain:
    """``unit``: what a contribution counts; ``up``/``down``: how the text says that the output rises or falls."""

    name: str
    context: str
    subject: str
    unit: str
    up: str
    down: str
    numeric: tuple[str, ...]
    categorical: tuple[str, ...]


DOMAINS = {
    d.name: d
    for d in (
        Domain("basket", "The model estimates the value of an order in dollars", "order", "dollars", "raises the estimate", "lowers the estimate",
               ("line count", "quantity", "mean discount", "mean tax", "parts", "suppliers", "ship lag", "balance"), ("priority", "status", "segment", "region")),
        Domain("toxic", "The model estimates how likely a document is abusive", "document", "points", "makes abuse more likely", "makes abuse less likely",
               (), ("language", "source", "length", "punctuation", "letter case", "repetition", "insult word", "web link")),
        Domain("junk", "The model estimates how likely a document is junk", "document", "points", "makes junk more likely", "makes junk less likely",
               ("characters", "word count", "line count", "word length", "nonletter share", "upper share", "digit share", "symbol share", "repeated lines", "exclamations"), ()),
        Domain("spend", "The model estimates how likely a customer is to spend more than most", "customer", "points", "makes high spending more likely", "makes high spending less likely",
               ("order count", "active months", "priorities"), ("market segment", "home nation", "home region", "positive balance", "urgent order", "open order")),
        Domain("activity", "The model estimates the value that a user brings in a day", "user day", "units", "raises the estimate", "lowers the estimate",
               ("clicks", "views", "errors", "signups", "purchases", "distinct props"), ()),
    )
}

#: style -> (domain, entries, hand-written ones); entry counts as published for the nine exemplar sets.
STYLES = {
    "basket_a": ("basket", 35, 5), "basket_b": ("basket", 22, 5), "basket_c": ("basket", 22, 5),
    "toxic_a": ("toxic", 30, 5), "toxic_b": ("toxic", 30, 5), "junk_a": ("junk", 30, 5), "junk_b": ("junk", 30, 5),
    "spend_a": ("spend", 30, 5), "spend_b": ("spend", 30, 5),
}
SET_ASIDE = 10  # entries of each style that serve as exemplars; the rest, 169, are evaluated

#: Published means, by technique: weighted A, C, F, S and total.
PUBLISHED_TECHNIQUES = (
    (1, 4.000, 4.000, 2.467, 0.850, 11.317), (2, 3.911, 4.000, 2.467, 0.872, 11.250), (3, 4.000, 4.000, 2.222, 1.056, 11.278),
    (4, 3.289, 3.511, 3.622, 3.749, 14.171), (5, 3.111, 3.422, 3.689, 3.708, 13.930), (6, 3.111, 3.289, 3.644, 3.669, 13.713),
    (7, 3.800, 3.800, 3.650, 3.702, 14.952), (8, 3.800, 3.800, 3.700, 3.734, 15.034), (9, 3.323, 3.538, 3.846, 3.843, 14.551),
    (10, 3.262, 3.631, 3.846, 3.890, 14.629), (11, 3.289, 3.333, 3.933, 3.983, 14.538), (12, 3.289, 3.467, 3.889, 3.988, 14.632),
    (13, 3.378, 3.422, 3.911, 3.977, 14.688),
)
#: Published means of the two best settings, by exemplar set.
PUBLISHED_SETS = (
    ("House 1", 3.733, 4.000, 3.800, 3.719, 15.252), ("House 2", 4.000, 4.000, 3.911, 3.836, 15.748), ("House 3", 4.000, 3.689, 3.933, 3.869, 15.491),
    ("Mush 1", 3.556, 3.600, 3.511, 4.000, 14.667), ("Mush 2", 1.760, 2.640, 3.920, 3.989, 12.309), ("PDF 1", 4.000, 2.400, 4.000, 3.977, 14.377),
    ("PDF 2", 0.000, 3.040, 3.840, 3.949, 10.829), ("Student 1", 4.000, 3.600, 3.960, 4.000, 15.560), ("Student 2", 3.840, 3.920, 4.000, 3.880, 15.640),
)
#: Published confusion counts (metric, human, grader, pairs).
PUBLISHED_CONFUSION = (
    ("accuracy", 0, 0, 15), ("accuracy", 0, 1, 1), ("accuracy", 1, 0, 1), ("accuracy", 1, 1, 33),
    ("completeness", 0, 0, 18), ("completeness", 0, 1, 0), ("completeness", 0, 2, 0), ("completeness", 1, 0, 0), ("completeness", 1, 1, 17),
    ("completeness", 1, 2, 0), ("completeness", 2, 0, 0), ("completeness", 2, 1, 2), ("completeness", 2, 2, 13),
)
#: Categories of the known-truth sets: (metric, category, grade, pairs).
CATEGORIES = (
    ("accuracy", "all values", 1, 16), ("accuracy", "some values", 1, 9), ("accuracy", "approximate values", 1, 9),
    ("accuracy", "value error", 0, 8), ("accuracy", "direction error", 0, 8),
    ("completeness", "everything", 2, 10), ("completeness", "directions only", 2, 5), ("completeness", "value or direction missing", 1, 17), ("completeness", "feature missing", 0, 18),
)
