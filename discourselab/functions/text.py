"""Text columns: normalisation, word n-grams, term expansion, sentiment by lexicon and rules."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass, field

import pandas as pd
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def clean_text(text: Column, keep_hyphen: bool = False) -> Column:
    """Lower case, letters, digits and single spaces only (hyphens too on request)."""
    kept = F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}\s-]" if keep_hyphen else r"[^\p{L}\p{N}\s]", "")
    return F.trim(F.regexp_replace(kept, r"\s+", " "))


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use(value)`` with the value computed once: inside functions over arrays it would be computed for every element."""
    return F.get(F.transform(F.array(value), lambda x: use(x)), F.lit(0))


def ngrams(tokens: Column, low: int, high: int) -> Column:
    """All runs of ``low`` to ``high`` tokens, joined by spaces."""
    return runs_of(tokens, range(low, high + 1))


def runs_of(tokens: Column, lengths: Iterable[int]) -> Column:
    """All runs of tokens of the given lengths, joined by spaces."""

    def runs(held: Column, k: int) -> Column:
        joined = F.transform(F.sequence(F.lit(1), F.size(held) - (k - 1)), lambda i: F.array_join(F.slice(held, i, k), " "))
        return F.when(F.size(held) >= k, joined).otherwise(F.array().cast("array<string>"))

    return let(tokens, lambda held: F.concat(*(held if k == 1 else runs(held, k) for k in lengths)))


def plural(term: Column) -> Column:
    return (
        F.when(term.rlike("(s|x|z|ch|sh)$"), F.concat(term, F.lit("es")))
        .when(term.rlike("[^aeiou]y$"), F.concat(F.regexp_replace(term, "y$", "i"), F.lit("es")))
        .otherwise(F.concat(term, F.lit("s")))
    )


def expand_terms(terms: DataFrame, plurals: bool = True, joined: bool = True, hyphen: bool = True) -> DataFrame:
    """(base, term): each term with its plural, written in one word and with hyphens."""
    base = F.col("base")
    forms = F.array(base, plural(base)) if plurals else F.array(base)
    variants = F.flatten(
        F.transform(
            forms,
            lambda f: F.array(f, *([F.replace(f, F.lit(" "), F.lit(""))] if joined else []), *([F.replace(f, F.lit(" "), F.lit("-"))] if hyphen else [])),
        )
    )
    return terms.select("base", F.explode(F.array_distinct(variants)).alias("term")).distinct()


@dataclass(frozen=True)
class Rules:
    """Rule words and weights of the sentiment score; all are parameters."""

    degree: dict[str, float] = field(default_factory=lambda: {"the": 0.293, "of": 0.293, "and": -0.293})
    negation: tuple[str, ...] = ("not", "is", "nicht", "non")
    contrast: tuple[str, ...] = ("to", "mais", "aber", "pero")
    damping: tuple[float, ...] = (1.0, 0.95, 0.9)
    flip: float = -0.74
    caps: float = 0.733
    before_contrast: float = 0.5
    after_contrast: float = 1.5
    exclamation: float = 0.292
    question: float = 0.18
    questions: float = 0.96
    spread: float = 15.0


#: Invented valences: the derogatory words of the corpus and a few of its common words.
LEXICON = {
    "idiot": -2.3, "moron": -2.2, "clown": -1.6, "scum": -2.9, "worthless": -1.9, "pathetic": -2.4, "stupid": -2.4, "trash": -1.7, "loser": -2.4, "disgusting": -3.1,
    "thing": 0.9, "ering": 1.4, "ther": 1.9, "tion": 2.4, "être": 1.1, "ment": 1.6, "lich": 1.2, "ung": 1.8, "ción": 1.3, "ado": 0.9,
}


def _map(values: dict[str, float]) -> Column:
    return F.create_map(*(F.lit(x) for pair in values.items() for x in pair))


def words_of(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(r"[\p{L}\p{N}']+"), F.lit(0))


def sentiment_arrow(text: Column, lexicon: dict[str, float] | None = None) -> Column:
    """The plain sum of ``sentiment`` over Arrow batches: the same scores, outside of generated code."""
    held, spread = dict(LEXICON if lexicon is None else lexicon), Rules().spread

    @F.pandas_udf("double")
    def score(texts: pd.Series) -> pd.Series:
        word = regex.compile(r"[\p{L}\p{N}']+")
        total = texts.fillna("").map(lambda x: sum(held.get(w.lower(), 0.0) for w in word.findall(x)))
        return total / (total * total + spread) ** 0.5

    return score(text)


def sentiment(text: Column, lexicon: dict[str, float] | None = None, rules: Rules | None = None, text_form: str = "raw") -> Column:
    """Score in [-1, 1] of a text, inside one row: no explode, no shuffle. Without rules, the plain sum.

    The rules read capitals and marks, which the ``clean`` form of a text has lost; ``raw`` keeps them.
    """
    text = clean_text(text) if text_form == "clean" else text
    held = _map(LEXICON if lexicon is None else lexicon)
    words = words_of(F.coalesce(text, F.lit("")))
    value = lambda w: F.coalesce(F.try_element_at(held, F.lower(w)), F.lit(0.0))
    if rules is None:
        total = F.aggregate(words, F.lit(0.0), lambda s, w: s + value(w))
        return total / F.sqrt(total * total + Rules().spread)
    degree = _map(rules.degree)
    shouted = lambda w: (F.upper(w) == w) & (F.lower(w) != w) & (F.length(w) > 1)
    steps = range(1, len(rules.damping) + 1)

    def facts(found: Column) -> Column:
        """Each word with those before it, and what holds for the whole text."""
        lowered = F.transform(found, lambda w: F.lower(w))
        before = [F.concat(F.array_repeat(F.lit(""), d), lowered).alias(f"b{d}") for d in steps]
        turn = F.array_position(F.transform(lowered, lambda w: w.isin(*rules.contrast)), True)
        return F.struct(F.arrays_zip(found.alias("w"), *before).alias("words"), F.exists(found, lambda w: ~shouted(w)).alias("mixed"), turn.alias("turn"))

    def one(x: Column, i: Column, mixed: Column, turn: Column) -> Column:
        v = value(x["w"])
        sign = F.signum(v)
        v = v + F.when(shouted(x["w"]) & mixed, sign * rules.caps).otherwise(0.0)
        denied = F.lit(False)
        for d, damp in zip(steps, rules.damping, strict=True):
            v = v + sign * damp * F.coalesce(F.try_element_at(degree, x[f"b{d}"]), F.lit(0.0))
            denied = denied | x[f"b{d}"].isin(*rules.negation)
        v = F.when(denied, v * rules.flip).otherwise(v)
        v = F.when((turn > 0) & (i + 1 < turn), v * rules.before_contrast).when((turn > 0) & (i + 1 > turn), v * rules.after_contrast).otherwise(v)
        return F.when(sign == 0, F.lit(0.0)).otherwise(v)

    parts = let(let(words, facts), lambda f: F.transform(F.filter(f["words"], lambda x: x["w"].isNotNull()), lambda x, i: one(x, i, f["mixed"], f["turn"])))
    total = F.aggregate(parts, F.lit(0.0), lambda s, v: s + v)
    marks = F.regexp_count(text, F.lit("!"))
    asks = F.regexp_count(text, F.lit(r"\?"))
    stress = F.least(marks, F.lit(4)) * rules.exclamation + F.when(asks > 3, rules.questions).when(asks > 1, asks * rules.question).otherwise(0.0)
    total = total + F.signum(total) * F.coalesce(stress, F.lit(0.0))
    return total / F.sqrt(total * total + rules.spread)


def polarity(score: Column, eps: float = 0.05) -> Column:
    return F.when(score >= eps, "positive").when(score <= -eps, "negative").otherwise("neutral")


def is_strong(score: Column, tau: float = 0.5) -> Column:
    """Strictly more than ``tau`` away from neutral."""
    return F.abs(score) > tau
