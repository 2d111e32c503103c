"""The text normaliser for classifiers: a chain of column functions, each with a switch."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

STEPS = ("newlines", "placeholders", "numbers", "symbols", "lower", "lemmas", "drop_long")
#: A sentinel of letters that survives the removal of symbols and is turned into the placeholder last.
_NUM = "zqnumqz"
NUMBER = "<NUM>"


def newlines(text: Column) -> Column:
    return F.translate(text, "\r\n", "  ")


def placeholders(text: Column) -> Column:
    return F.regexp_replace(F.regexp_replace(text, r"https?://[^ ]+", " urlref "), r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+", " mailref ")


def numbers(text: Column) -> Column:
    return F.regexp_replace(text, r"[+-]?[0-9]+(?:[.,][0-9]+)*", f" {_NUM} ")


def symbols(text: Column) -> Column:
    text = F.regexp_replace(F.regexp_replace(text, "-{2,}", "-"), "_{2,}", "_")
    return F.trim(F.regexp_replace(F.regexp_replace(text, r"[^\p{L}\p{N} _^=+*/<>-]+", " "), " {2,}", " "))


def lemma(token: Column) -> Column:
    """A few suffix rules for English; an approximation, a model's lemmatiser may be passed instead."""
    n = F.length(token)
    return (
        F.when(token == _NUM, token).when((n > 4) & token.endswith("ies"), F.regexp_replace(token, "ies$", "y")).when((n > 5) & token.endswith("ing"), F.regexp_replace(token, "ing$", ""))
        .when((n > 4) & token.endswith("ed"), F.regexp_replace(token, "ed$", "")).when((n > 3) & token.endswith("s") & ~token.endswith("ss"), F.regexp_replace(token, "s$", "")).otherwise(token)
    )


def tokens(text: Column, steps: tuple[str, ...] = STEPS, lemmatise=lemma, longest: int = 100) -> Column:
    """Tokens of a text after the steps named; 'lemmas' uses lemmatise, a function of a token column."""
    for name, step in (("newlines", newlines), ("placeholders", placeholders), ("numbers", numbers), ("symbols", symbols), ("lower", F.lower)):
        if name in steps:
            text = step(text)
    out = F.filter(F.split(text, " "), lambda w: w != "")
    if "lemmas" in steps and lemmatise is not None:
        out = F.transform(out, lambda w: lemmatise(w))
    if "drop_long" in steps:
        out = F.filter(out, lambda w: F.length(w) <= longest)
    return F.transform(out, lambda w: F.when(w == _NUM, F.lit(NUMBER)).otherwise(w))


def _words(x: str, drop: bool = True) -> str:
    x = f"list_filter(string_split({x}, ' '), lambda w: w <> '')"
    return f"list_filter({x}, lambda w: length(w) <= 100)" if drop else x


def tokens_sql(x: str, steps: tuple[str, ...]) -> str:
    """DuckDB SQL of tokens() without lemmas."""
    if "newlines" in steps:
        x = f"translate({x}, chr(13) || chr(10), '  ')"
    if "placeholders" in steps:
        x = f"regexp_replace(regexp_replace({x}, 'https?://[^ ]+', ' urlref ', 'g'), '[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+', ' mailref ', 'g')"
    if "numbers" in steps:
        x = f"regexp_replace({x}, '[+-]?[0-9]+(?:[.,][0-9]+)*', ' {_NUM} ', 'g')"
    if "symbols" in steps:
        x = f"trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace({x}, '-{{2,}}', '-', 'g'), '_{{2,}}', '_', 'g'), '[^\\p{{L}}\\p{{N}} _^=+*/<>-]+', ' ', 'g'), ' {{2,}}', ' ', 'g'))"
    if "lower" in steps:
        x = f"lower({x})"
    return f"list_transform({_words(x, 'drop_long' in steps)}, lambda w: CASE WHEN w = '{_NUM}' THEN '{NUMBER}' ELSE w END)"
