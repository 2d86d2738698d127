"""Quality rules: a table of thresholds compiled into one projection of built-in expressions.

Every document gets its measures and a verdict in a single scan without a shuffle or a user function. A null text
is an empty one (no words, so it fails); repeated rows and null ids are judged row by row; columns of the input that
clash with a measure do not matter, because only the text and the named id columns are read.
"""

from __future__ import annotations

from collections.abc import Sequence
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from utilmine.llm.shared import SPACE_CLASS, SPACES, let, words

#: Characters that count as symbols.
SYMBOLS = "#*$%&|<>"
#: Frequent short words of English, German, French and Spanish.
STOP_WORDS = (
    "the of and to in is that it for was on are as with be at by this from or a "
    "der die und den von zu das mit sich des auf für ist im dem nicht ein eine "
    "de la le et les du un une en que des est pour dans par sur avec "
    "el los las y se con no por su para del al lo como es"
).split()
WINDOW = 5


class Rule(NamedTuple):
    """A document passes when low <= numerator / denominator <= high; a denominator of zero passes."""

    name: str
    numerator: str
    denominator: str
    low: float | None
    high: float | None


#: The production thresholds. base rules come first in the verdict and are reported on their own.
BASE_RULES = (
    Rule("enough_words", "n_words", "one", 10, None),
    Rule("repeated_words", "n_repeat_words", "n_words", None, 0.20),
)
RULES = (
    Rule("mean_word_length", "word_chars", "n_words", 2.0, 14.0),
    Rule("symbols_per_word", "n_symbols", "n_words", None, 0.30),
    Rule("duplicate_lines", "n_dup_lines", "n_lines", None, 0.30),
    Rule("stop_words", "n_stop_words", "n_words", 0.02, None),
    Rule("upper_case", "n_upper", "word_chars", None, 0.60),
)


def _repeat_words(tokens: Column) -> Column:
    """Words under five-word windows whose content occurs at least twice in the text.

    Windows are named by a 64-bit hash and sorted with their position, so that equal ones are neighbours; the
    positions of the repeated ones, sorted again, give the length of the union of their spans.
    """

    def of_hashes(h: Column) -> Column:
        starts = F.transform(F.sequence(F.lit(1), F.size(h) - (WINDOW - 1)), lambda i: F.struct(F.xxhash64(*(F.get(h, i - 1 + k) for k in range(WINDOW))).alias("h"), i.alias("i")))

        def of_sorted(s: Column) -> Column:
            same = lambda x, j: F.coalesce(F.get(s, j)["h"] == x["h"], F.lit(False))
            again = F.transform(F.filter(s, lambda x, k: same(x, k - 1) | same(x, k + 1)), lambda x: x["i"])
            return let(F.sort_array(again), lambda p: F.aggregate(p, F.struct(F.lit(0).alias("n"), F.lit(-WINDOW).alias("at")), lambda acc, x: F.struct((acc["n"] + F.least(F.lit(WINDOW), x - acc["at"])).alias("n"), x.alias("at")), lambda acc: acc["n"]))

        return let(F.sort_array(starts), of_sorted)

    some = F.size(tokens) > WINDOW
    return F.when(some, let(F.transform(tokens, lambda w: F.xxhash64(w)), of_hashes)).otherwise(F.lit(0)).cast("long")


def measures(text: Column) -> dict[str, Column]:
    """Name to expression over a text column; `tokens` must be in the frame already (see score)."""
    full, tokens = F.coalesce(text, F.lit("")), F.col("__tokens")
    count = lambda chars: F.length(full) - F.length(F.translate(full, chars, ""))
    lines = F.filter(F.split(full, "\n"), lambda x: F.btrim(x, F.lit(SPACES)) != "")
    out = {
        "n_words": F.size(tokens),
        "word_chars": F.length(F.translate(full, SPACES, "")),
        "n_symbols": count(SYMBOLS),
        "n_dup_lines": let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))),
        "n_repeat_words": _repeat_words(tokens),
        "n_lines": F.size(lines),
        "n_stop_words": F.size(tokens) - F.size(F.filter(tokens, lambda w: ~F.rtrim(F.lower(w), F.lit(".,;:!?")).isin(STOP_WORDS))),
        "n_upper": count("ABCDEFGHIJKLMNOPQRSTUVWXYZÄÖÜÀÂÇÉÈÊËÎÏÔÛÙÑÁÍÓÚ"),
        "one": F.lit(1),
    }
    return {k: v.cast("long") for k, v in out.items()}


def passes(rules: Sequence[Rule]) -> Column:
    """The conjunction of rules, by multiplication so that integers stay exact where the bound is one."""
    ok = F.lit(True)
    for r in rules:
        num, den = F.col(f"__m.{r.numerator}"), F.col(f"__m.{r.denominator}")
        if r.low is not None:
            ok = ok & (num >= F.lit(r.low) * den)
        if r.high is not None:
            ok = ok & (100 * num <= F.lit(round(100 * r.high, 6)) * den)
    return ok


def score(docs: DataFrame, keep: Sequence[str] = ("doc_id",), text: str = "text", rules: Sequence[Rule] = RULES, base: Sequence[Rule] = BASE_RULES) -> DataFrame:
    """The columns in keep, the measures, base_failed and kept, for each row of docs."""
    cols = [F.col(k) for k in keep]
    split = docs.select(*cols, F.col(text).alias("__text"), words(F.col(text)).alias("__tokens"))
    made = split.select(*cols, F.struct(*(v.alias(k) for k, v in measures(F.col("__text")).items())).alias("__m"))
    return made.select(*cols, "__m.*", (~passes(base)).alias("base_failed"), (passes(base) & passes(rules)).alias("kept"))
