"""Document rules that keep mathematical text, rejected candidates for comparison, and one pass that applies them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Whole words that the given tables plant in toxic documents.
INSULTS = ("idiot", "stupid", "clown", "trash", "scum", "moron", "loser", "worthless", "pathetic", "disgusting")
PUNCT = r"[\p{P}\p{S}]"
Rule = Callable[[], Column]


def n_words(text: Column) -> Column:
    return F.size(F.filter(F.split(text, "[ \t\r\n]+"), lambda w: w != ""))


def lorem(text: Column, max_words: int = 100) -> Column:
    return F.lower(text).contains("lorem ipsum") & (n_words(text) <= max_words)


def punct_ratio(text: Column, lang: Column, cut: float = 0.3, marks: str = PUNCT, only: str = "en") -> Column:
    return (lang == only) & (F.regexp_count(text, F.lit(marks)) > F.length(text) * F.lit(cut))


def blocklist(text: Column, words: tuple[str, ...] = INSULTS) -> Column:
    """Whole words in any case. Long lists belong in a table: see blocklist_join."""
    return F.arrays_overlap(F.split(F.lower(text), r"[^\p{L}\p{N}_]+"), F.array(*map(F.lit, words)))


def blocklist_join(docs: DataFrame, words: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Ids of documents with a word of a table: a semi join that Spark broadcasts or shuffles by the list's size."""
    tokens = docs.select(id_col, F.explode(F.array_distinct(F.split(F.lower("text"), r"[^\p{L}\p{N}_]+"))).alias("word"))
    return tokens.join(words.select("word"), "word", "left_semi").select(id_col).distinct()


def unicode_error(text: Column) -> Column:
    """The replacement character, C1 controls, or non-characters."""
    return text.rlike(r"[\x{FFFD}\x{80}-\x{9F}\x{FDD0}-\x{FDEF}\x{FFFE}\x{FFFF}]")


def retained() -> dict[str, Column]:
    text, lang = F.col("text"), F.col("lang")
    return {"lorem": lorem(text), "punctuation": punct_ratio(text, lang), "blocklist": blocklist(text), "unicode": unicode_error(text)}


def candidates() -> dict[str, Column]:
    """Usual web rules, off by default because they hurt mathematical text; kept to measure that."""
    text = F.col("text")
    lines = F.filter(F.split(text, "\n"), lambda x: F.trim(x) != "")
    return {
        "curly_brace": text.contains("{"), "javascript": F.lower(text).contains("javascript"), "few_words": n_words(text) < 50,
        "few_sentences": F.regexp_count(text, F.lit(r"[.!?]")) < 3, "no_terminal_punctuation": F.size(F.filter(lines, lambda x: x.rlike(r"[.!?\"']$"))) * 2 < F.size(lines),
        "repeated_lines": F.size(F.array_distinct(lines)) * 10 < F.size(lines) * 7, "digits": F.regexp_count(text, F.lit("[0-9]")) * 10 > F.length(text),
    }


def apply(docs: DataFrame, rules: dict[str, Column] | None = None, mode: str = "all") -> DataFrame:
    """docs with reasons array<string> and kept, in one pass. mode: all reasons, or the first."""
    rules = rules or retained()
    hit = F.array_compact(F.array(*(F.when(c, F.lit(name)) for name, c in rules.items())))
    return docs.withColumn("reasons", hit if mode == "all" else F.slice(hit, 1, 1)).withColumn("kept", F.size("reasons") == 0)


def ledger(applied: DataFrame, names: list[str]) -> DataFrame:
    """(rule, hits, only_hits): documents a rule hits, and those that no other does; 'any' is their union. One aggregation."""
    sums = [F.sum(F.array_contains("reasons", n).cast("long")).alias(f"h_{n}") for n in names] + [F.sum((F.array_contains("reasons", n) & (F.size("reasons") == 1)).cast("long")).alias(f"o_{n}") for n in names]
    one = applied.agg(*sums, F.sum((~F.col("kept")).cast("long")).alias("any"))
    rows = F.array(*(F.struct(F.lit(n).alias("rule"), F.col(f"h_{n}").alias("hits"), F.col(f"o_{n}").alias("only_hits")) for n in names), F.struct(F.lit("any").alias("rule"), F.col("any").alias("hits"), F.col("any").alias("only_hits")))
    return one.select(F.inline(rows))


def damage_report(docs: DataFrame, rules: dict[str, Column]) -> DataFrame:
    """(rule, positives_hit, negatives_hit) over labelled rows (quality 1 or 0): what a rule costs in good documents."""
    sums = [F.sum((c & (F.col("quality") == q)).cast("long")).alias(f"{n}{q}") for n, c in rules.items() for q in (1, 0)]
    rows = F.array(*(F.struct(F.lit(n).alias("rule"), F.col(f"{n}1").alias("positives_hit"), F.col(f"{n}0").alias("negatives_hit")) for n in rules))
    return docs.agg(*sums).select(F.inline(rows))
