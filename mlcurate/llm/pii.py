"""Personal data: expressions propose spans, checksums confirm them, nearby words adjust the score.

Everything is a DataFrame expression. A kind's spans come from its matches and from
the text between them (``split`` by the same expression), so offsets are counted in
code points. Expressions are written possessively: they match what the plain forms
match, without backtracking, so very long runs of digits or letters stay linear.

Kinds, in order: email, ip (parts to 255), card (13 to 19 digits, Luhn), phone (9 to
15 digits after a plus); added by the method: iban (mod 97), tel (national form
``(ddd) ddd-dddd``). A span's score starts from its kind's prior; a word that goes
with the kind within 40 characters before it raises the score, a word that speaks
against it (order, part, serial numbers) lowers it.

Defined cases: null and empty texts have no spans; repeated rows repeat; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_PART = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]?[0-9])"
#: kind -> (expression, cheap test that a text may hold one)
PATTERNS = {
    "email": (r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", lambda t: t.contains("@")),
    "ip": (r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}", lambda t: t.rlike(r"[0-9]\.[0-9]")),
    "card": (r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){12,18}+(?![\x20-]?[0-9])", lambda t: t.rlike(r"[0-9](?:[\x20-]?[0-9]){12}")),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda t: t.contains("+")),
    "iban": (r"(?<![A-Z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}+(?:\x20?[A-Z0-9]{1,3})?(?![A-Z0-9])", lambda t: t.rlike(r"[A-Z]{2}[0-9]{2}\x20?[A-Z0-9]{4}")),
    "tel": (r"\([0-9]{3}\)\x20?[0-9]{3}-[0-9]{4}(?![0-9])", lambda t: t.rlike(r"\([0-9]{3}\)")),
}
BASE = ("email", "ip", "card", "phone")
PRIOR = {"email": 0.9, "ip": 0.6, "card": 0.8, "phone": 0.7, "iban": 0.9, "tel": 0.5}
FOR = {
    "email": "mail|contact|kontakt|correo|courriel|write to",
    "ip": "server|host|address|adresse|login|client|ip",
    "card": "card|visa|master|credit|karte|carte|tarjeta|payment",
    "phone": "phone|tel|call|mobil|fax|anruf|telef",
    "iban": "iban|account|konto|compte|cuenta|bank",
    "tel": "phone|tel|call|mobil|fax|anruf|telef",
}
AGAINST = "order|part|serial|isbn|version|invoice|bestell|num[eé]ro de s[eé]rie|sku"
CONTEXT = 40


def luhn(digits: Column) -> Column:
    """Does this string of digits pass Luhn?"""
    doubled = lambda c, i: F.when(i % 2 == 1, F.when(c.cast("int") > 4, c.cast("int") * 2 - 9).otherwise(c.cast("int") * 2)).otherwise(c.cast("int"))
    return F.aggregate(F.transform(F.split(F.reverse(digits), ""), doubled), F.lit(0), lambda a, x: a + x) % 10 == 0


def mod97(iban: Column) -> Column:
    """Does this IBAN (no spaces) pass mod 97?"""
    turned = F.concat(F.substring(iban, 5, 64), F.substring(iban, 1, 4))
    value = lambda c: F.when(c.rlike("[0-9]"), c.cast("int")).otherwise(F.ascii(c) - 55)
    return F.aggregate(F.split(turned, ""), F.lit(0), lambda a, c: (a * F.when(value(c) > 9, 100).otherwise(10) + value(c)) % 97) == 1


def _valid(kind: str, m: Column) -> Column:
    digits = F.regexp_replace(m, "[^0-9]", "")
    return {
        "email": lambda: F.lit(True),
        "ip": lambda: m.rlike(rf"^{_PART}(?:\.{_PART}){{3}}$"),
        "card": lambda: luhn(digits),
        "phone": lambda: F.length(digits).between(9, 15),
        "iban": lambda: mod97(F.regexp_replace(m, " ", "")),
        "tel": lambda: F.lit(True),
    }[kind]()


_SPAN = "array<struct<start:int,stop:int,score:double>>"


def _spans(kind: str, text: Column, found: Column, between: Column) -> Column:
    """Confirmed spans of one kind, from its matches and the pieces between them."""
    step = lambda a, i: F.named_struct(
        F.lit("at"), (a["at"] + F.length(F.get(between, i)) + F.length(F.get(found, i))).cast("int"),
        F.lit("out"), F.when(
            _valid(kind, F.get(found, i)),
            F.array_append(a["out"], F.named_struct(
                F.lit("start"), (a["at"] + F.length(F.get(between, i))).cast("int"),
                F.lit("stop"), (a["at"] + F.length(F.get(between, i)) + F.length(F.get(found, i))).cast("int"),
                F.lit("score"), _score(kind, F.right(F.get(between, i), F.lit(CONTEXT))))),
        ).otherwise(a["out"]),
    )
    start = F.named_struct(F.lit("at"), F.lit(0), F.lit("out"), F.array().cast(_SPAN))
    return F.when(F.size(found) > 0, F.aggregate(F.sequence(F.lit(0), F.size(found) - 1), start, step, lambda a: a["out"])).otherwise(F.array().cast(_SPAN))


def _score(kind: str, before: Column) -> Column:
    low = F.lower(before)
    up, down = F.when(low.rlike(FOR[kind]), 0.1).otherwise(0.0), F.when(low.rlike(AGAINST), 0.3).otherwise(0.0)
    return F.least(F.lit(1.0), F.lit(PRIOR[kind]) + up - down)


def find(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with one array column ``pii_<kind>`` of (start, stop, score) per kind; stop is exclusive."""
    df = docs.withColumn("__t", F.coalesce(F.col(text), F.lit("")))
    none = F.array().cast("array<string>")
    t = F.col("__t")
    df = df.withColumns({f"__m_{k}": F.when(test(t), F.regexp_extract_all(t, F.lit(p), F.lit(0))).otherwise(none) for k, (p, test) in PATTERNS.items()})
    df = df.withColumns({f"__b_{k}": F.when(F.size(f"__m_{k}") > 0, F.split(t, p, -1)).otherwise(none) for k, (p, _) in PATTERNS.items()})
    df = df.withColumns({f"pii_{k}": _spans(k, t, F.col(f"__m_{k}"), F.col(f"__b_{k}")) for k in PATTERNS})
    return df.drop("__t", *[f"__{x}_{k}" for k in PATTERNS for x in "mb"])


def _said(kind: str) -> Column:
    return F.transform(f"pii_{kind}", lambda s: F.concat(F.lit(f"{kind}:"), s["start"].cast("string"), F.lit(":"), s["stop"].cast("string")))


def _joined(kinds) -> Column:
    return F.array_join(F.concat(*map(_said, kinds)), ",")


def _named(kind: str, least: float) -> Column:
    sure = F.filter(f"pii_{kind}", lambda s: s["score"] >= least)
    return F.transform(sure, lambda s: F.struct(s["start"].alias("start"), s["stop"].alias("stop"), F.lit(kind).alias("kind")))


def digest(docs: DataFrame) -> DataFrame:
    """Per document: counts, hash of the base spans, all spans, and how sure the surest is."""
    df = find(docs.select(F.col("doc_id").cast("long"), "text"))
    scores = F.concat(*[F.transform(f"pii_{k}", lambda s: s["score"]) for k in PATTERNS])
    return df.select(
        "doc_id", *[F.size(f"pii_{k}").cast("long").alias(f"n_{k}") for k in BASE],
        F.sha2(_joined(BASE), 256).alias("base_sha256"), _joined(PATTERNS).alias("spans"),
        F.round(F.array_max(scores), 6).alias("top_score"),
    )


def redact(docs: DataFrame, least: float = 0.5, text: str = "text") -> DataFrame:
    """``docs`` with every span that scores ``least`` or more replaced by ``[kind]``; overlapping spans become one."""
    df = find(docs, text)
    all_spans = F.array_sort(F.flatten(F.array(*[_named(k, least) for k in PATTERNS])))
    step = lambda a, s: F.when(s["start"] < a["at"], a).otherwise(F.named_struct(
        F.lit("at"), s["stop"], F.lit("out"), F.concat(a["out"], F.substring(F.col(text), a["at"] + 1, s["start"] - a["at"]), F.lit("["), s["kind"], F.lit("]"))))
    start = F.named_struct(F.lit("at"), F.lit(0), F.lit("out"), F.lit(""))
    done = F.aggregate(all_spans, start, step, lambda a: F.concat(a["out"], F.substring(F.col(text), a["at"] + 1, F.length(text))))
    return df.withColumn(text, F.when(F.col(text).isNotNull(), done)).drop(*[f"pii_{k}" for k in PATTERNS])
