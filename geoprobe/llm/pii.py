"""Personal data by patterns, checksum validators and context, in SQL functions alone.

For each kind a regular expression proposes spans, leftmost and non-overlapping; the text between them (`split` by the
same pattern) gives their places in code points. Validators confirm: octets of at most 255, Luhn, digit counts, the
mod-97 rule of account numbers. Whole words within 40 characters before or after adjust a score. The four base kinds
(email, ip, card, phone) stay whatever their score; the added kinds (iban, ssn) need a score of 0.5.

The patterns carry possessive quantifiers and a "not inside a run" test, which leave their matches as they are but
keep scanning linear on very long runs. Regular expressions run only on texts that hold a necessary character or digit
group. Null text has no spans; repeated rows are treated alike; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The patterns that propose spans.
EMAIL = r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?:\G|(?<![0-9]))[0-9]++(?:\.[0-9]++){3}"
CARD = r"[0-9](?:[\x20-]?[0-9])++"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
IBAN = r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]){11,30}(?![A-Za-z0-9])"
SSN = r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"
KINDS = ("email", "ip", "card", "phone", "iban", "ssn")
BASE = 4
LEAST_SCORE, REACH = 0.5, 40

_SPAN = "array<struct<kind:int,start:int,end:int,score:double>>"


def _digits(text: Column) -> Column:
    return F.regexp_replace(text, "[^0-9]", "")


def _octets(match: Column) -> Column:
    return match.rlike(r"^(?:0*(?:25[0-5]|2[0-4][0-9]|[01]?[0-9]{1,2})(?:\.(?!$)|$)){4}$")


def _luhn(match: Column) -> Column:
    digits = _digits(match)
    return F.length(digits).between(16, 19) & F.call_function("luhn_check", digits)


def _mod97(match: Column) -> Column:
    """First four characters moved to the end, letters as 10 to 35, remainder 1 modulo 97."""
    packed = F.regexp_replace(match, " ", "")
    turned = F.concat(F.substring(packed, 5, 40), F.substring(packed, 1, 4))

    def step(rest, c):
        code = F.ascii(c)
        return F.when(code >= 65, (rest * 100 + code - 55) % 97).otherwise((rest * 10 + code - 48) % 97)

    return F.aggregate(F.filter(F.split(turned, ""), lambda c: c != ""), F.lit(0), step) == 1


#: Kind: pattern, necessary test on the text, validator, score, context words, words that speak against.
_RULES = {
    "email": (EMAIL, lambda t: F.contains(t, F.lit("@")), None, 0.9, "e?-?mails?|contact|write|correo|courriel", None),
    "ip": (IP, lambda t: t.rlike(r"[0-9]\.[0-9]++\.[0-9]"), _octets, 0.6, "ip|address(?:es)?|servers?|hosts?|login", "versions?|releases?|sections?"),
    "card": (CARD, lambda t: t.rlike(r"[0-9](?:[\x20-]?[0-9]){15}"), _luhn, 0.8, "cards?|visa|credit|payment|karte|tarjeta|carte", "isbn|serial"),
    "phone": (PHONE, lambda t: F.contains(t, F.lit("+")), lambda m: F.length(_digits(m)).between(8, 15), 0.6, "(?:tele)?phone|tel|call|mobile|fax", None),
    "iban": (IBAN, lambda t: t.rlike(r"[A-Z]{2}[0-9]{2}"), _mod97, 0.7, "iban|bank|accounts?|konto|cuenta|compte", None),
    "ssn": (SSN, lambda t: t.rlike(r"[0-9]{3}-[0-9]{2}-[0-9]{4}"), lambda m: ~m.rlike("^(?:000|666|9..)-|-00-|-0000$"), 0.3, "ssn|social|security", "orders?|parts?"),
}


def _near(rule: tuple, before: Column, after: Column) -> Column:
    """The kind's own score, raised by context words and lowered by words that speak against."""
    _, _, _, score, words, against = rule
    around = F.concat_ws(" ", F.lower(F.right(before, F.lit(REACH))), F.lower(F.left(after, F.lit(REACH))))
    whole = lambda some: around.rlike(rf"(?<![\p{{L}}\p{{N}}])(?:{some})(?![\p{{L}}\p{{N}}])")
    out = F.lit(score) + F.when(whole(words), 0.3).otherwise(0.0)
    return F.least(F.lit(1.0), out - F.when(whole(against), 0.3).otherwise(0.0) if against else out)


def _spans(number: int, kind: str) -> Column:
    """The confirmed spans of one kind from its matches and the pieces between them."""
    rule = _RULES[kind]
    matches, pieces = F.col(f"m_{kind}"), F.col(f"p_{kind}")
    rows = F.arrays_zip(matches.alias("m"), F.slice(pieces, 1, F.size(matches)).alias("b"), F.slice(pieces, 2, F.size(matches)).alias("a"))

    def step(so_far, row):
        match = row["m"]
        start = so_far["at"] + F.char_length(row["b"])
        end = start + F.char_length(match)
        score = _near(rule, row["b"], row["a"])
        valid = rule[2](match) if rule[2] else F.lit(True)
        if number >= BASE:
            valid = valid & (score >= LEAST_SCORE)
        own = F.array(F.struct(F.lit(number).alias("kind"), start.alias("start"), end.alias("end"), score.alias("score"))).cast(_SPAN)
        return F.struct(end.alias("at"), F.when(valid, F.concat(so_far["spans"], own)).otherwise(so_far["spans"]).alias("spans"))

    return F.aggregate(rows, F.struct(F.lit(0).alias("at"), F.array().cast(_SPAN).alias("spans")), step, lambda x: x["spans"])


def find_personal_data(docs: DataFrame) -> DataFrame:
    """doc_id, text and spans (kind, start, end, score) ordered by kind, then start."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    text, none = F.col("text"), F.array().cast("array<string>")
    found = []
    for kind in KINDS:
        pattern, needed = _RULES[kind][:2]
        found.append(F.when(needed(text), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))).otherwise(none).alias(f"m_{kind}"))
        found.append(F.when(needed(text), F.split(text, pattern, -1)).otherwise(none).alias(f"p_{kind}"))
    return docs.select("doc_id", "text", *found).select("doc_id", "text", F.concat(*(_spans(i, kind) for i, kind in enumerate(KINDS))).alias("spans"))


def named(spans: Column) -> Column:
    """kind:start:end of every span, joined by commas."""
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def redacted(docs: DataFrame) -> DataFrame:
    """doc_id, text with every span replaced by its kind in angle brackets (of overlapping spans the first counts)."""
    names = F.array(*map(F.lit, KINDS))
    order = F.array_sort(F.transform("spans", lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end"))))

    def step(done, s):
        free = s["start"] >= done["at"]
        piece = F.concat(done["out"], F.substring(F.col("text"), done["at"] + 1, s["start"] - done["at"]), F.lit("<"), F.element_at(names, s["kind"] + 1), F.lit(">"))
        return F.struct(F.when(free, s["end"]).otherwise(F.greatest(s["end"], done["at"])).alias("at"), F.when(free, piece).otherwise(done["out"]).alias("out"))

    masked = F.aggregate(order, F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), step, lambda x: F.concat(x["out"], F.substring(F.col("text"), x["at"] + 1, F.char_length("text"))))
    return find_personal_data(docs).select("doc_id", masked.alias("text"))
