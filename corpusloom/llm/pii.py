"""Personal data: base patterns, and further candidates that boosted trees select. DataFrame operations only.

Generators of high recall propose spans that may overlap: numbers in the shapes of phones and cards without what the
base patterns ask for, addresses with a masked at sign or dots. Each candidate has features of format and context. A
candidate is confirmed if a base span of its kind overlaps it, or if with its masks undone it is itself one. How often
candidates of the same features are confirmed is counted over all documents; small boosted trees are fitted to these
counts (their number depends on the features alone), as expressions that Spark compiles. For each kind the least score at
which held-out documents confirm nine in ten is the threshold; candidates above it that touch no base span of any kind and
pass the kind's own check are added. Base spans always stay.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusloom.llm.filters import wrapped

KINDS = ("email", "ip", "card", "phone")
#: The base patterns, written so that Java matches them without recursion and in linear time. A run of characters that
#: may begin a match is tried at its first character only, or where the last match ended: later ones can't do better.
BASE = (
    r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}",
    r"[0-9](?:[ -]?[0-9])++",
    r"\+[0-9][ ().0-9-]+[0-9]",
)
_AT, _DOT = r"(?:@|\(at\)|\[at\]| at )", r"(?:\.|\(dot\)|\[dot\]| dot )"
CANDIDATES = (
    rf"(?i)(?<![a-z0-9._%+-])[a-z0-9._%+-]{{1,64}}+ ?{_AT} ?[a-z0-9-]{{1,63}}+(?: ?{_DOT} ?[a-z][a-z0-9-]{{1,23}}+){{1,4}}",
    r"(?i)(?<![0-9.])[0-9]{1,3}(?: ?(?:\[\.\]|\(\.\)|\[dot\]|\(dot\)|\.) ?[0-9]{1,3}){3}(?![0-9])",
    r"(?<![0-9])[0-9]{4}(?:[ ._/-]?[0-9]{4}){2,3}(?:[ ._/-]?[0-9]{1,3})?(?![0-9])",
    r"(?<![0-9])\(?[0-9]{2,4}\)?[ ./-]{1,2}[0-9]{3,4}(?:[ ./-][0-9]{3,4}){1,2}(?![0-9])",
)
#: What a text must have for a pattern to be worth trying.
_BASE_GUARD = (r"@", r"[0-9]\.[0-9]", r"[0-9]", r"\+[0-9]")
_CANDIDATE_GUARD = (r"(?i)@|[(\[]at[)\]]| at ?[a-z0-9-]+ ?(?:\.|[(\[]dot[)\]]| dot )", r"(?i)[0-9] ?[\[(.]", r"[0-9]{4}[ ._/-]?[0-9]{4}", r"[0-9]{2}\)?[ ./-]{1,2}[0-9]{3}")
_CUES = (r"e-?mail|mail|contact|write|reach", r"\bip\b|host|server|addr|login|from", r"card|visa|master|amex|credit|debit|pay", r"tel|phone|call|fax|mobile|whatsapp|sms|ring")
_OCTET = r"^0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])$"
CONTEXT = 24


def _digits(hit: Column) -> Column:
    return F.regexp_replace(hit, "[^0-9]", "")


def _octets_ok(hit: Column) -> Column:
    return F.forall(F.split(F.regexp_replace(hit, "[^0-9]+", "."), r"\."), lambda x: x.rlike(_OCTET))


def _passes(kind: int, hit: Column) -> Column:
    """The base pattern's own check of a match."""
    n = F.length(_digits(hit))
    return (F.lit(True), F.forall(F.split(hit, r"\."), lambda x: x.rlike(_OCTET)), n.between(12, 19) & F.call_function("luhn_check", _digits(hit)), n.between(9, 15))[kind]


def _undone(kind: int, hit: Column) -> Column:
    """Whether a masked candidate is a valid one of its kind without the masks. A bare word 'at' masks only beside a 'dot'."""
    if kind == 0:
        masked = hit.rlike(r"(?i)[(\[]at[)\]]| at .* dot ")
        plain = F.regexp_replace(F.regexp_replace(hit, r"(?i) ?(?:\(at\)|\[at\]| at ) ?", "@"), r"(?i) ?(?:\(dot\)|\[dot\]| dot ) ?", ".")
        return masked & plain.rlike(r"^[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+$")
    if kind == 1:
        return hit.rlike(r"(?i)[\[(]") & _octets_ok(hit)
    return hit.rlike("[._/]") & _passes(2, _digits(hit)) if kind == 2 else F.lit(False)


def _may_add(kind: int, hit: Column) -> Column:
    """The own check of a candidate that is to be added."""
    n = F.length(_digits(hit))
    return (hit.contains("@") | _undone(0, hit), _octets_ok(hit), n.between(12, 19) & F.call_function("luhn_check", _digits(hit)), n.between(9, 15))[kind]


def _find(df: DataFrame, prefix: str, patterns: tuple[str, ...], guards: tuple[str, ...]) -> DataFrame:
    """Columns prefix0.. : arrays of (start, end, hit), by code points. Matches and the texts between them give the places."""
    none = F.array().cast("array<string>")
    df = df.withColumns({f"__h{k}": F.when(F.col("__text").rlike(g), F.regexp_extract_all("__text", F.lit(p), F.lit(0))).otherwise(none) for k, (p, g) in enumerate(zip(patterns, guards, strict=True))})
    df = df.withColumns({f"__g{k}": F.when(F.size(f"__h{k}") > 0, F.split("__text", p, -1)).otherwise(none) for k, p in enumerate(patterns)})
    out = {}
    for k in range(len(patterns)):
        both = F.zip_with(F.col(f"__h{k}"), F.slice(F.col(f"__g{k}"), F.lit(1), F.size(f"__h{k}")), lambda h, g: F.struct(h.alias("h"), F.length(g).alias("g"), F.length(h).alias("n")))
        start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int,hit:string>>").alias("out"))
        step = lambda a, x: F.struct(
            (a["at"] + x["g"] + x["n"]).alias("at"),
            F.concat(a["out"], F.array(F.struct((a["at"] + x["g"]).alias("start"), (a["at"] + x["g"] + x["n"]).alias("end"), x["h"].alias("hit")))).alias("out"),
        )
        out[f"{prefix}{k}"] = F.aggregate(both, start, step, lambda a: a["out"])
    return df.withColumns(out).drop(*(f"__{x}{k}" for x in "hg" for k in range(len(patterns))))


def _with_base(df: DataFrame) -> DataFrame:
    """__base: array of (start, kind, end) in order; kind is an index of KINDS."""
    df = _find(df, "__b", BASE, _BASE_GUARD)

    def valid(k: int) -> Column:  # a lambda's second parameter would be the index
        return F.transform(F.filter(F.col(f"__b{k}"), lambda x: _passes(k, x["hit"])), lambda x: F.struct(x["start"].alias("start"), F.lit(k).alias("kind"), x["end"].alias("end")))

    return df.withColumn("__base", F.array_sort(F.concat(*map(valid, range(4))))).drop(*(f"__b{k}" for k in range(4)))


def _bucket(n: Column, *cuts: int) -> Column:
    return sum(((n >= c).cast("int") for c in cuts[1:]), (n >= cuts[0]).cast("int"))


#: Names of features; each has few values.
FEATURES = ("kind", "digits", "marks", "parens", "cue", "letter_after", "line_start", "length")


def _with_candidates(df: DataFrame) -> DataFrame:
    """__cand: array of (start, end, may_add, features..., touches, met). touches: it overlaps a base span; met: it is confirmed."""
    df = _find(df, "__c", CANDIDATES, _CANDIDATE_GUARD)

    def each(k: int) -> Column:
        def features(x: Column) -> Column:
            hit = x["hit"]
            # substring counts from one, and a start below one is a window that begins before the text
            before = F.substring(F.col("__text"), F.greatest(x["start"] - CONTEXT + 1, F.lit(1)), F.least(x["start"], F.lit(CONTEXT)))
            after = F.substring(F.col("__text"), x["end"] + 1, F.lit(1))
            return F.struct(
                x["start"].alias("start"), x["end"].alias("end"), _may_add(k, hit).alias("may_add"), F.lit(k).alias("kind"),
                _bucket(F.length(_digits(hit)), 1, 9, 12, 16).alias("digits"),
                F.when(hit.rlike(r"(?i)[\[(](?:at|dot|\.)[\])]"), 3).when(hit.rlike("(?i) (?:at|dot) "), 2).when(hit.rlike("[./_]"), 1).otherwise(0).alias("marks"),
                hit.rlike(r"\([0-9]").cast("int").alias("parens"), before.rlike("(?i)(?:" + _CUES[k] + ")").cast("int").alias("cue"),
                after.rlike(r"[\p{L}\p{N}]").cast("int").alias("letter_after"), ((x["start"] == 0) | before.endswith("\n")).cast("int").alias("line_start"),
                _bucket(F.length(hit), 10, 16, 24).alias("length"),
                F.exists(F.col("__base"), lambda b: (b["start"] < x["end"]) & (x["start"] < b["end"])).alias("touches"),
                (F.exists(F.col("__base"), lambda b: (b["kind"] == k) & (b["start"] < x["end"]) & (x["start"] < b["end"])) | _undone(k, hit)).alias("met"),
            )

        return F.transform(F.col(f"__c{k}"), features)

    return df.withColumn("__cand", F.concat(*map(each, range(4)))).drop(*(f"__c{k}" for k in range(4)))


@dataclass
class Boosted:
    """Trees of two levels over equalities of features, and the threshold of each kind."""

    trees: list[tuple] = field(default_factory=list)
    start: float = 0.0
    thresholds: tuple[float, ...] = (2.0,) * len(KINDS)

    def score(self, x: Column) -> Column:
        test = lambda split: x[FEATURES[split[0]]] == split[1]
        leaf = lambda split, a, b: F.when(test(split), F.lit(a)).otherwise(F.lit(b))
        total = reduce(lambda s, t: s + F.when(test(t[0]), leaf(*t[1])).otherwise(leaf(*t[2])), self.trees, F.lit(self.start))
        return 1 / (1 + F.exp(-total))

    def keep(self, x: Column) -> Column:
        cut = reduce(lambda c, k: F.when(x["kind"] == k, F.lit(float(self.thresholds[k]))).otherwise(c), range(len(KINDS)), F.lit(2.0))
        return x["may_add"] & ~x["touches"] & (self.score(x) >= cut)


def boost(table: np.ndarray, yes: np.ndarray, no: np.ndarray, rounds: int = 24, rate: float = 0.3) -> tuple[list[tuple], float]:
    """Trees on rows of feature values with counts of either outcome; Newton steps of the logistic loss."""
    splits = [(f, int(v)) for f in range(table.shape[1]) for v in np.unique(table[:, f])]
    hits = np.array([table[:, f] == v for f, v in splits])
    n = yes + no
    start = float(np.log((yes.sum() + 1) / (no.sum() + 1)))
    score, trees = np.full(len(table), start), []

    def best(grad: np.ndarray, hess: np.ndarray) -> tuple[tuple[int, int], float, float, np.ndarray]:
        g, h = hits @ grad, hits @ hess
        rest_g, rest_h = grad.sum() - g, hess.sum() - h
        at = int((g**2 / (h + 1) + rest_g**2 / (rest_h + 1)).argmax())
        return splits[at], rate * g[at] / (h[at] + 1), rate * rest_g[at] / (rest_h[at] + 1), hits[at]

    for _ in range(rounds if len(table) else 0):
        p = 1 / (1 + np.exp(-score))
        grad, hess = yes - n * p, n * p * (1 - p)
        root, _, _, on = best(grad, hess)
        left, right = best(grad * on, hess * on), best(grad * ~on, hess * ~on)
        trees.append((root, left[:3], right[:3]))
        score = score + np.where(on, np.where(left[3], left[1], left[2]), np.where(right[3], right[1], right[2]))
    return trees, start


def _as_text(docs: DataFrame, text_col: str) -> DataFrame:
    return docs.withColumn("__text", F.coalesce(F.col(text_col).cast("string"), F.lit("")))


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", precision: float = 0.9, rounds: int = 24) -> Boosted:
    """Counts features over all documents and fits the trees to documents with an even checksum of the id, thresholds to the others."""
    half = F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(2)), F.lit(0))
    found = _with_candidates(_with_base(_as_text(docs.select(id_col, text_col), text_col).withColumn("__half", half))).select("__half", F.explode("__cand").alias("x"))
    counts = found.groupBy("__half", *(F.col(f"x.{f}").alias(f) for f in FEATURES)).agg(F.sum(F.col("x.met").cast("int")).alias("yes"), F.count("*").alias("all"))
    rows = counts.collect()  # at most as many as features have combinations: 4 x 5 x 4 x 2 x 2 x 2 x 2 x 4, twice
    take = lambda h: [np.array([[r[c] for c in cols] for r in rows if r["__half"] == h], float).reshape(-1, len(cols)) for cols in (FEATURES, ("yes", "all"))]
    x, y = take(0)
    trees, start = boost(x.astype(int), y[:, 0], y[:, 1] - y[:, 0], rounds)
    model = Boosted(trees, start)
    x, y = take(1)
    total = np.full(len(x), start)
    for (rf, rv), (lsplit, la, lb), (rsplit, ra, rb) in trees:
        total += np.where(x[:, rf] == rv, np.where(x[:, lsplit[0]] == lsplit[1], la, lb), np.where(x[:, rsplit[0]] == rsplit[1], ra, rb))
    p, cuts = 1 / (1 + np.exp(-total)), []
    for k in range(len(KINDS)):
        own = np.flatnonzero(x[:, 0] == k)
        own = own[np.argsort(-p[own])]
        right = np.cumsum(y[own, 0]) / np.maximum(1, np.cumsum(y[own, 1]))
        good = np.flatnonzero((right >= precision) & (np.append(p[own][1:], -1)[: len(own)] < p[own]))
        cuts.append(float(p[own][good[-1]]) - 1e-9 if len(good) else 2.0)
    model.thresholds = tuple(cuts)
    return model


def with_spans(docs: DataFrame, model: Boosted, text_col: str = "text") -> DataFrame:
    """docs with __base and __spans, sorted arrays of (start, kind, end); map-only."""
    df = _with_candidates(_with_base(_as_text(docs, text_col)))
    added = F.transform(F.filter("__cand", model.keep), lambda x: F.struct(x["start"].alias("start"), x["kind"].alias("kind"), x["end"].alias("end")))
    return df.withColumn("__spans", F.array_sort(F.array_distinct(F.concat("__base", added)))).drop("__cand")


def _named(spans: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def digests(docs: DataFrame, model: Boosted, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans), one row for each row of docs; null counts as the empty text."""
    df = with_spans(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), model)

    def count(k: int) -> Column:
        return F.size(F.filter("__base", lambda s: s["kind"] == k)).cast("long").alias(f"n_{KINDS[k]}")

    return df.select("doc_id", *map(count, range(4)), F.sha2(_named(F.col("__base")), 256).alias("base_sha256"), _named(F.col("__spans")).alias("spans"))


def redact(docs: DataFrame, model: Boosted, text_col: str = "text", length_col: str | None = None) -> DataFrame:
    """docs with each span's characters replaced by [EMAIL], [IP], [CARD] or [PHONE], overlapping spans by the first one's.

    Null texts stay null. length_col, where given, gets the new text's length.
    """
    df = with_spans(wrapped(docs, text=F.col(text_col)), model, "text")
    tags = F.array(*(F.lit(f"[{k.upper()}]") for k in KINDS))
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    step = lambda a, s: F.when(s["start"] < a["at"], F.struct(F.greatest(a["at"], s["end"]).alias("at"), a["out"].alias("out"))).otherwise(
        F.struct(s["end"].alias("at"), F.concat(a["out"], F.substring(F.col("__text"), a["at"] + 1, s["start"] - a["at"]), F.get(tags, s["kind"])).alias("out"))
    )
    clean = F.aggregate("__spans", start, step, lambda a: F.concat(a["out"], F.substring(F.col("__text"), a["at"] + 1, F.length("__text"))))
    found = F.size("__spans") > 0
    df = df.withColumn("clean", F.when(found, clean).otherwise(F.col("text")))
    new = {text_col: F.col("clean")}
    if length_col:
        new[length_col] = F.when(found, F.length("clean").cast(docs.schema[length_col].dataType)).otherwise(F.col("__row")[length_col])
    return df.select(*(new.get(c, F.col("__row")[c]).alias(c) for c in docs.columns))
