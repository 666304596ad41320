r"""Personal data: proposed by patterns, confirmed by checksums, weighed by context words.

Every kind is a regular expression (rewritten without backtracking but matching the same spans),
a validator and a context pattern.  A proposal starts at the kind's prior, a passed checksum and
each side's context raise it; the four base kinds are kept whenever they validate, the added
kinds only when their score reaches ``THRESHOLD``.  All of it is DataFrame expressions: the text
is split at the matches, and running lengths of the parts give code-point offsets.

Defined cases: a null text is empty and has no spans; matches that fail validation are dropped
and not retried; very long runs take linear time; repeated ids and rows each give a row; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from aggclust.llm.batches import documents

THRESHOLD, CONTEXT = 0.6, 40


@dataclass(frozen=True)
class Kind:
    name: str
    pattern: str
    trigger: str  # a cheap necessary condition, SQL on column _t
    valid: str  # SQL on the match m
    prior: float
    checked: float  # what a passed validation adds
    words: str  # context words
    base: bool = False


_DIGITS = "regexp_replace(m, '[^0-9]', '')"
_LUHN = (
    f"(length({_DIGITS}) BETWEEN 13 AND 19 AND aggregate(sequence(1, length({_DIGITS})), 0, (a, i) -> a + "
    f"CASE WHEN (length({_DIGITS}) - i) % 2 = 0 THEN int(substring({_DIGITS}, i, 1)) "
    f"WHEN int(substring({_DIGITS}, i, 1)) > 4 THEN int(substring({_DIGITS}, i, 1)) * 2 - 9 "
    f"ELSE int(substring({_DIGITS}, i, 1)) * 2 END) % 10 = 0)"
)
_PARTS = "forall(split(m, '[.]'), p -> CASE WHEN length(regexp_replace(p, '^0+(?=.)', '')) <= 3 THEN int(regexp_replace(p, '^0+(?=.)', '')) <= 255 ELSE false END)"
_PLAIN = "replace(m, ' ', '')"
# Letters count as two digits (A is 10), so their place value is 100.
_MOD97 = (
    f"(length({_PLAIN}) BETWEEN 15 AND 34 AND aggregate(split(concat(substring({_PLAIN}, 5), left({_PLAIN}, 4)), ''), 0, (a, c) -> "
    "CASE WHEN c = '' THEN a WHEN c BETWEEN '0' AND '9' THEN (a * 10 + int(c)) % 97 ELSE (a * 100 + ascii(c) - 55) % 97 END) = 1)"
)

# The countries of the public IBAN registry by the length of their account numbers.
IBAN_LENGTHS = {
    15: "NO", 16: "BE", 18: "DK FI FK FO GL NL SD", 19: "MK SI", 20: "AT BA EE KZ LT LU MN XK", 21: "CH CR HR LI LV",
    22: "BG BH DE GB GE IE ME RS VA", 23: "AE GI IL IQ OM SO TL", 24: "AD CZ ES MD PK RO SA SE SK TN VG", 25: "LY PT ST", 26: "IS TR",
    27: "BI DJ FR GR IT MC MR SM", 28: "AL AZ BY CY DO GT HN HU LB NI PL SV", 29: "BR EG PS QA UA", 30: "JO KW MU YE", 31: "MT SC", 32: "LC", 33: "RU",
}
_IBAN = "|".join(f"(?:{'|'.join(names.split())})[0-9]{{2}}(?:\\x20?[A-Z0-9]){{{n - 4}}}" for n, names in IBAN_LENGTHS.items())

KINDS = (
    Kind("email", r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "contains(_t, '@')", "true", 0.7, 0.1, "mail|contact|write|reply", True),
    Kind("ip", r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", "contains(_t, '.') AND _t RLIKE '[0-9][.][0-9]'", _PARTS, 0.5, 0.2, "ip|host|server|addr|login", True),
    Kind("card", r"[0-9](?:[\x20-]?[0-9])++", "_t RLIKE '[0-9]'", _LUHN, 0.3, 0.5, "card|visa|credit|payment|account", True),
    Kind("phone", r"\+[0-9][\x20().0-9-]+[0-9]", "contains(_t, '+')", f"length({_DIGITS}) BETWEEN 9 AND 15", 0.5, 0.2, "phone|tel|call|mobile|fax", True),
    Kind("iban", rf"(?<![A-Z0-9])(?:{_IBAN})(?![A-Za-z0-9])", "_t RLIKE '[A-Z]{2}[0-9]{2}'", _MOD97, 0.2, 0.6, "iban|bank|account|konto|compte|cuenta"),
    Kind("ssn", r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])", "_t RLIKE '[0-9]-[0-9]{2}-[0-9]'", "NOT m RLIKE '^(000|666|9)|-00-|-0000$'", 0.2, 0.15, "ssn|social security|tax id"),
    Kind("passport", r"(?<![A-Za-z0-9])[A-Z]{1,2}[0-9]{6,8}(?![A-Za-z0-9])", "_t RLIKE '[A-Z][0-9]{6}'", "true", 0.3, 0.0, "passport|passeport|reisepass|pasaporte|identity"),
)


def _quoted(text: str) -> str:
    return "r'" + text + "'"


def spans_of(kind: Kind) -> Column:
    """array<struct<start, end, score>> of one kind in column ``_t`` (code points, end exclusive)."""
    none = "CAST(array() AS array<struct<start:int,end:int,score:double>>)"
    near = _quoted(f"(?i)(?<![a-z])(?:{kind.words})")
    # x.o stands before the match x.m, and x.`2` behind it.
    scored = (
        f"named_struct('start', a.at + length(x.o), 'end', a.at + length(x.o) + length(x.m), 'score', "
        f"round(least(1D, {kind.prior + kind.checked:.3f}D + CASE WHEN right(x.o, {CONTEXT}) RLIKE {near} THEN 0.3D ELSE 0D END "
        f"+ CASE WHEN left(x.`2`, {CONTEXT}) RLIKE {near} THEN 0.1D ELSE 0D END), 3))"
    )
    walked = (
        f"aggregate(arrays_zip(z.o, z.m, slice(z.o, 2, size(z.o))), named_struct('at', 0, 'found', {none}), (a, x) -> "
        f"named_struct('at', a.at + length(x.o) + coalesce(length(x.m), 0), 'found', CASE WHEN x.m IS NULL THEN a.found "
        f"WHEN {_on(kind.valid, 'x.m')} THEN array_append(a.found, {scored}) ELSE a.found END), a -> a.found)"
    )
    if not kind.base:
        walked = f"filter({walked}, s -> s.score >= {THRESHOLD}D)"
    parts = f"array(named_struct('o', split(_t, {_quoted(kind.pattern)}, -1), 'm', regexp_extract_all(_t, {_quoted(kind.pattern)}, 0)))"
    return F.expr(f"CASE WHEN {kind.trigger} THEN element_at(transform({parts}, z -> {walked}), 1) ELSE {none} END")


def _on(sql: str, value: str) -> str:
    return re.sub(r"\bm\b", lambda _: value, sql)


def find_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", kinds: tuple[Kind, ...] = KINDS) -> DataFrame:
    """doc_id and one array of (start, end, score) per kind."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("_t"))
    return texts.select("doc_id", *(spans_of(k).alias(k.name) for k in kinds))


def listed(kinds: tuple[Kind, ...]) -> Column:
    """All spans of ``kinds`` as kind:start:end, comma-joined."""
    def named(kind: Kind) -> Column:
        return F.transform(F.col(kind.name), lambda s: F.concat_ws(":", F.lit(kind.name), s["start"].cast("string"), s["end"].cast("string")))

    parts = [named(k) for k in kinds]
    return F.array_join(F.concat(*parts), ",")


def pii(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    base = tuple(k for k in KINDS if k.base)
    counts = [F.size(k.name).cast("long").alias(f"n_{k.name}") for k in base]
    return find_spans(docs, id_col, text_col).select("doc_id", *counts, F.sha2(listed(base), 256).alias("base_sha256"), listed(KINDS).alias("spans"))


def mask(docs: DataFrame, text_col: str = "text", kinds: tuple[Kind, ...] = KINDS) -> DataFrame:
    """``docs`` with every span that ``find_spans`` lists replaced by its kind in brackets.

    All spans are those of the text as it came.  Of spans that overlap, the one that begins first
    (the longest of these) gives the name, and all that any of them covers goes.  Null texts stay
    null; other columns, whatever their names, are untouched.
    """
    tagged = ", ".join(f"transform(k.{kind.name}, s -> named_struct('b', s.start, 'l', s.start - s.end, 'n', '[{kind.name.upper()}]'))" for kind in kinds)
    step = (
        "CASE WHEN s.b >= a.at THEN named_struct('at', s.b - s.l, 'out', concat(a.out, substring(t, a.at + 1, s.b - a.at), s.n)) "
        "WHEN s.b - s.l > a.at THEN named_struct('at', s.b - s.l, 'out', a.out) ELSE a END"
    )
    built = f"aggregate(sorted, named_struct('at', 0, 'out', ''), (a, s) -> {step}, a -> concat(a.out, substring(t, a.at + 1, length(t) - a.at)))"
    row = docs.select(F.struct("*").alias("_row"), F.col(f"`{text_col}`").cast("string").alias("_t"))
    found = row.select("_row", "_t", F.struct(*(spans_of(k).alias(k.name) for k in kinds)).alias("k"))
    found = found.select("_row", F.col("_t").alias("t"), F.expr(f"array_sort(concat({tagged}))").alias("sorted"))
    new = F.expr(f"CASE WHEN size(sorted) > 0 THEN {built} ELSE t END")
    return found.select(*((new if c == text_col else F.col("_row").getField(c)).alias(c) for c in docs.columns))


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii(documents(spark, sf_dir))
