"""Personal data by DataFrame functions alone: patterns propose spans, checksums confirm, context scores.

A pattern's matches come from ``regexp_extract_all`` and the text between them from ``split`` by the
same pattern, so a match's place is the running sum of both lengths, taken over the row's own arrays: no
row leaves its task. Running sums go by stretches of the root of the number of matches, so that a text of
very many matches costs little more than its length. Patterns use possessive runs and look-behinds that
make each scan linear; they accept exactly the documented base patterns (leftmost, non-overlapping).

Offsets count code points, ends are exclusive. Null texts are empty; rows without a finding still come
back; repeated rows and null ids each get a row of their own.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Kinds in their order, what must occur in a text at all, and the proposing patterns.
KINDS = ("email", "ip", "card", "phone", "iban")
BASE_KINDS = KINDS[:4]
TRIGGER = {"email": "@", "ip": ".", "card": None, "phone": "+", "iban": None}
PATTERN = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9]++(?:[ -][0-9]++)*+",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){11,30}(?![A-Za-z0-9])",
}
PRIOR = {"email": 0.9, "ip": 0.6, "card": 0.8, "phone": 0.5, "iban": 0.9}
CONTEXT = {
    "email": r"(?i)\b(e-?mail|contact|write|correo|courriel|kontakt)\b",
    "ip": r"(?i)\b(ip|address|host|server|login)\b",
    "card": r"(?i)\b(card|visa|mastercard|credit|debit|karte|carte|tarjeta)\b",
    "phone": r"(?i)\b(phone|tel|call|mobile|fax|telefon|appelez|llame)\b",
    "iban": r"(?i)\b(iban|account|bank|konto|compte|cuenta)\b",
}
#: Code points on each side of a span in which context words count.
CONTEXT_WINDOW = 48


def luhn(digits: Column) -> Column:
    """Whether a string of at most 19 digits passes Luhn's check."""
    padded, total = F.lpad(digits, 19, "0"), F.lit(0)
    for i in range(19):
        d = F.ascii(F.substring(padded, i + 1, 1)) - 48
        total = total + (d if i % 2 == 0 else 2 * d - F.when(d > 4, 9).otherwise(0))
    return total % 10 == 0


def mod97(iban: Column) -> Column:
    """Whether an IBAN without blanks leaves 1 when divided by 97."""
    turned = F.concat(F.substring(iban, 5, 40), F.substring(iban, 1, 4))
    step = lambda acc, c: F.when(c.between("0", "9"), (acc * 10 + F.ascii(c) - 48) % 97).otherwise((acc * 100 + F.ascii(c) - 55) % 97)
    return F.aggregate(F.split(turned, ""), F.lit(0), step) == 1


def confirmed(kind: str, match: Column) -> Column:
    """The validator of a kind; a match that fails is dropped without a retry."""
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        return F.forall(F.split(match, r"\."), lambda x: x.cast("double") <= 255)
    if kind == "iban":
        return mod97(F.regexp_replace(match, " ", ""))
    digits = F.regexp_replace(match, "[^0-9]", "")
    n = F.length(digits)
    return F.when(n.between(12, 19), luhn(digits)).otherwise(False) if kind == "card" else n.between(9, 15)


def bound(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once, wherever and how often the body uses it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def running(values: Column, total: Callable[[Column], Column], step: Callable[[Column, Column], Column], body: Callable[[Callable[[Column], Column]], Column]) -> Column:
    """``body`` of a function that gives the total of ``values`` up to and with a place; ``total`` adds up an
    array, ``step`` two totals. Whole stretches are added up once."""

    def stretches(v: Column) -> Column:
        n = F.greatest(F.lit(1), F.ceil(F.sqrt(F.size(v))).cast("int"))
        starts = F.sequence(F.lit(0), F.greatest(F.lit(0), F.size(v) - 1), n)
        return bound(F.struct(n.alias("n"), F.transform(starts, lambda b: total(F.slice(v, b + 1, n))).alias("whole")), lambda s: body(upto(v, s)))

    def upto(v: Column, s: Column) -> Callable[[Column], Column]:
        inside = lambda i: i % s["n"]
        return lambda i: step(total(F.slice(s["whole"], F.lit(1), F.floor(i / s["n"]).cast("int"))), total(F.slice(v, i - inside(i) + 1, inside(i) + 1)))

    return bound(values, stretches)


def added(values: Column) -> Column:
    return F.aggregate(values, F.lit(0), lambda a, x: a + x)


def greatest_of(values: Column) -> Column:
    return F.coalesce(F.array_max(values), F.lit(0))


def with_spans(df: DataFrame, text_col: str, name: str) -> DataFrame:
    """``df`` with the confirmed spans of its text: (start, rank, kind, end, score) by start and kind."""
    columns = [F.col(f"`{c}`") for c in df.columns]
    held = "__packflow"
    found = df.select(F.struct(*columns).alias("doc"), F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit("")).alias("text"))
    digit = F.col("text").rlike("[0-9]")
    nothing = F.array().cast("array<string>")
    matches = {k: F.when(F.col("text").contains(TRIGGER[k]) if TRIGGER[k] else digit, F.regexp_extract_all("text", F.lit(PATTERN[k]), F.lit(0))).otherwise(nothing) for k in KINDS}
    found = found.withColumns({f"{held}m_{k}": c for k, c in matches.items()})
    found = found.withColumns({f"{held}g_{k}": F.when(F.size(f"{held}m_{k}") > 0, F.split("text", PATTERN[k], -1)).otherwise(nothing) for k in KINDS})

    def spans_of(rank: int, k: str) -> Column:
        match, gap = F.col(f"{held}m_{k}"), F.col(f"{held}g_{k}")

        def one(upto: Callable[[Column], Column]) -> Column:
            def span(m: Column, i: Column) -> Column:
                near = F.concat(F.right(F.get(gap, i), F.lit(CONTEXT_WINDOW)), F.lit(" "), F.left(F.get(gap, i + 1), F.lit(CONTEXT_WINDOW)))
                score = F.least(F.lit(1.0), F.lit(PRIOR[k]) + F.when(near.rlike(CONTEXT[k]), 0.3).otherwise(0.0))
                end = upto(i)
                whole = F.struct((end - F.length(m)).alias("start"), F.lit(rank).alias("rank"), F.lit(k).alias("kind"), end.alias("end"), score.alias("score"))
                return F.when(confirmed(k, m), whole)

            return F.array_compact(F.transform(match, span))

        lengths = F.transform(match, lambda m, i: F.length(F.get(gap, i)) + F.length(m))
        return F.when(F.size(match) > 0, running(lengths, added, lambda a, b: a + b, one)).otherwise(F.array())

    every = F.sort_array(F.concat(*(spans_of(rank, k) for rank, k in enumerate(KINDS))))
    return found.select("doc", "text", every.alias(name))


def find_pii(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: its spans (kind, start, end, score) by start and kind."""
    at = df.columns.index(id_col)
    found = with_spans(df.toDF(*(f"c{i}" for i in range(len(df.columns)))), f"c{df.columns.index(text_col)}", "found")
    shown = F.transform("found", lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end"), s["score"].alias("score")))
    return found.select(F.col(f"doc.c{at}").alias(id_col), shown.alias("spans"))


def pii_digest(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Counts of the base kinds, the digest of the base spans, and all spans as text."""
    told = lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))
    base = F.filter("spans", lambda s: s["kind"].isin(*BASE_KINDS))
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long")
    return find_pii(df, id_col, text_col).select(
        id_col,
        *(count(k).alias(f"n_{k}") for k in BASE_KINDS),
        F.sha2(F.array_join(F.transform(base, told), ",").cast("binary"), 256).alias("base_sha256"),
        F.array_join(F.transform("spans", told), ",").alias("spans"),
        count("iban").alias("n_iban"),
        F.round(F.array_max(F.transform("spans", lambda s: s["score"])), 3).alias("top_score"),
    )


def cut_out(text: Column, body: Callable[[Callable[[Column, Column], Column]], Column]) -> Column:
    """``body`` of a function that gives the text from one place to another. It looks into blocks of the
    text alone, as finding a place costs as many steps as there are characters before it."""

    def over(t: Column) -> Column:
        n = F.greatest(F.lit(1024), (8 * F.sqrt(F.length(t["text"]))).cast("int"))
        return bound(F.struct(n.alias("n"), F.transform(F.sequence(F.lit(0), F.length(t["text"]), n), lambda b: t["text"].substr(b + 1, n)).alias("blocks")), lambda s: body(between(s)))

    def between(s: Column) -> Callable[[Column, Column], Column]:
        def take(low: Column, high: Column) -> Column:
            first, last = F.floor(low / s["n"]).cast("int"), F.floor(high / s["n"]).cast("int")
            block = lambda i: F.coalesce(F.get(s["blocks"], i), F.lit(""))
            middle = F.array_join(F.slice(s["blocks"], first + 2, F.greatest(F.lit(0), last - first - 1)), "")
            apart = F.concat(block(first).substr(low % s["n"] + 1, s["n"]), middle, block(last).substr(F.lit(1), high % s["n"]))
            return F.when(first == last, block(first).substr(low % s["n"] + 1, high - low)).otherwise(apart)

        return take

    return bound(F.struct(text.alias("text")), over)


def redact(df: DataFrame, text_col: str = "text", min_score: float = 0.5) -> DataFrame:
    """The same rows and columns, with every span of ``min_score`` or more replaced by its kind in brackets;
    a span that begins inside another goes with it."""
    kept = df.columns
    at = kept.index(text_col)
    rows = with_spans(df.toDF(*(f"c{i}" for i in range(len(kept)))), f"c{at}", "found")
    rows = rows.withColumn("found", F.filter("found", lambda s: s["score"] >= min_score))
    ends = F.transform("found", lambda s: s["end"])

    def without(take: Callable[[Column, Column], Column]) -> Column:
        def pieces(upto: Callable[[Column], Column]) -> Column:
            def piece(s: Column, i: Column) -> Column:
                name = F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]"))
                before = F.when(i > 0, upto(i - 1)).otherwise(F.lit(0))
                return bound(before, lambda b: F.when(s["start"] >= b, F.concat(take(b, s["start"]), name)).otherwise(F.lit("")))

            return F.array_join(F.transform("found", piece), "")

        return F.concat(running(ends, greatest_of, F.greatest, pieces), take(greatest_of(ends), F.length("text")))

    clean = F.when(F.size("found") > 0, cut_out(F.col("text"), without)).otherwise(F.col(f"doc.c{at}"))
    return rows.select(*(clean.alias(c) if i == at else F.col(f"doc.c{i}").alias(c) for i, c in enumerate(kept)))
