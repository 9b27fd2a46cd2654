"""Personal data spans: patterns propose, checksums confirm, words nearby adjust the score. DataFrame functions only.

Base kinds (email, ip, card, phone) follow fixed patterns, leftmost and without overlap per kind; a match that fails
its check is dropped and not tried again inside. Two kinds are added: iban (mod-97 over country, check digits and
account) and ssn (three-part number whose parts are in range), each kept only from a score of `threshold` on.
A score is 0.4 for the pattern, 0.4 for a passed checksum or range, 0.2 for a context word within `reach` characters
before the span; base spans stay at any score.

Positions are code points, end exclusive: the text is split at the matches, and lengths of pieces and matches add up.
The patterns are written with possessive loops, and those that could start anywhere inside a long run start only at
the run's head or where the last match ended, so a text is read in linear time and without deep recursion; the matches
are those of the plain patterns.

Defined cases: null text is empty and has no spans; null ids, extra columns, repeated rows pass through row by row.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import whole

#: Account numbers: countries by the number's length without spaces; other countries may have any length.
ACCOUNTS = {
    15: "NO", 16: "BE", 18: "DK FI FK FO GL NL SD", 19: "MK SI", 20: "AT BA EE KZ LT LU MN XK", 21: "CH CR HR LI LV", 22: "BG BH DE GB GE IE ME RS VA",
    23: "AE GI IL IQ OM SO TL", 24: "AD CZ ES MD PK RO SA SE SK TN VG", 25: "LY PT ST", 26: "IS TR", 27: "BI DJ FR GR IT MC MR SM", 28: "AL AZ BY CY DO GT HU LB NI PL SV",
    29: "BR EG PS QA UA", 30: "JO KW MU YE", 31: "MT SC", 32: "LC", 33: "RU",
}
_BY_LENGTH = "|".join(rf"(?:{c.replace(' ', '|')})[0-9]{{2}}(?: ?[A-Z0-9]){{{n - 4}}}" for n, c in ACCOUNTS.items())
_OTHERS = rf"(?!{'|'.join(ACCOUNTS.values()).replace(' ', '|')})[A-Z]{{2}}[0-9]{{2}}(?: ?[A-Z0-9]){{11,30}}"
#: The patterns, with possessive loops.
LOCAL = "A-Za-z0-9._%+-"
PATTERNS = {
    "email": rf"(?:(?<![{LOCAL}])|\G)[{LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:(?<![0-9])|\G)[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[ -]?[0-9]){15,}+",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
    "iban": rf"(?<![A-Za-z0-9])(?:{_BY_LENGTH}|{_OTHERS})(?![A-Za-z0-9])",
    "ssn": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
}
#: What a text must hold for a pattern to be tried.
NEEDS = {"email": "@", "ip": ".", "phone": "+", "ssn": "-"}
BASE = ("email", "ip", "card", "phone")
CONTEXT = {
    "email": ("mail", "contact", "kontakt", "correo"),
    "ip": ("ip", "host", "server", "address"),
    "card": ("card", "visa", "karte", "carte", "tarjeta", "credit", "payment"),
    "phone": ("phone", "call", "tel", "mobile", "fax"),
    "iban": ("iban", "account", "bank", "konto", "compte", "cuenta"),
    "ssn": ("ssn", "social", "security", "tax"),
}
REACH = 40
THRESHOLD = 0.6


def _digits(span: Column) -> Column:
    return F.regexp_replace(span, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """Whether a digit string passes the Luhn check."""
    each = F.transform(F.split(F.reverse(digits), ""), lambda d, i: d.cast("int") * (1 + i % 2))
    return F.aggregate(each, F.lit(0), lambda a, d: a + F.when(d > 9, d - 9).otherwise(d)) % 10 == 0


def mod97(span: Column) -> Column:
    """Whether an account number with country letters and check digits leaves 1 modulo 97 (letters count from 10)."""
    plain = F.replace(span, F.lit(" "), F.lit(""))
    moved = F.concat(F.substr(plain, F.lit(5)), F.substring(plain, 1, 4))
    step = lambda a, c: F.when(c.between("0", "9"), (a * 10 + c.try_cast("int")) % 97).otherwise((a * 100 + F.ascii(c) - 55) % 97)
    return F.aggregate(F.split(moved, ""), F.lit(0), step) == 1


def _octets(span: Column) -> Column:
    small = lambda p: (F.length(F.ltrim(p, F.lit("0"))) <= 3) & (F.coalesce(F.substring(F.ltrim(p, F.lit("0")), 1, 3).try_cast("int"), F.lit(0)) <= 255)
    return F.forall(F.split(span, r"\."), small)


def _ssn_parts(span: Column) -> Column:
    return ~F.substring(span, 1, 3).isin("000", "666") & (F.substring(span, 1, 1) != "9") & (F.substring(span, 5, 2) != "00") & (F.substring(span, 8, 4) != "0000")


CHECKS = {
    "email": lambda s: F.lit(True),
    "ip": _octets,
    "card": lambda s: F.length(_digits(s)).between(16, 19) & luhn(_digits(s)),
    "phone": lambda s: F.length(_digits(s)).between(8, 15),
    "iban": mod97,
    "ssn": _ssn_parts,
}


def spans_of(text: Column, kind: str, reach: int = REACH, threshold: float = THRESHOLD) -> Column:
    """array<struct<kind, start int, end int, score double>> of one kind."""
    pattern = PATTERNS[kind]
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    gaps = F.split(text, pattern, -1)
    none = F.array().cast("array<struct<m:string,s:int>>")
    placed = F.aggregate(
        F.zip_with(found, F.slice(gaps, F.lit(1), F.size(found)), lambda m, g: F.struct(m.alias("m"), F.length(g).alias("g"))),
        F.struct(F.lit(0).alias("at"), none.alias("all")),
        lambda a, x: F.struct((a["at"] + x["g"] + F.length(x["m"])).alias("at"), F.concat(a["all"], F.array(F.struct(x["m"].alias("m"), (a["at"] + x["g"]).alias("s")))).alias("all")),
        lambda a: a["all"],
    )
    kept = F.filter(placed, lambda x: CHECKS[kind](x["m"]))

    def scored(x: Column) -> Column:
        near = F.lower(F.substr(text, F.greatest(F.lit(1), x["s"] + 1 - reach), F.least(F.lit(reach), x["s"])))
        met = reduce(lambda a, b: a | b, [near.contains(w) for w in CONTEXT[kind]])
        sure = 0.4 if kind in ("email", "phone") else 0.8
        return F.struct(F.lit(kind).alias("kind"), x["s"].alias("start"), (x["s"] + F.length(x["m"])).alias("end"), F.round(F.lit(sure) + F.when(met, 0.2).otherwise(0.0), 2).alias("score"))

    out = F.transform(kept, scored)
    if kind not in BASE:
        out = F.filter(out, lambda x: x["score"] >= (threshold if kind == "iban" else 0.9))
    empty = F.array().cast("array<struct<kind:string,start:int,end:int,score:double>>")
    return F.when(text.contains(NEEDS[kind]) if kind in NEEDS else F.regexp_like(text, F.lit(pattern)), out).otherwise(empty)


def find_pii(docs: DataFrame, text: str = "text", reach: int = REACH, threshold: float = THRESHOLD) -> DataFrame:
    """docs with an array of spans for each kind (__email ... __ssn)."""
    body = whole(text)
    return docs.withColumns({f"__{kind}": spans_of(body, kind, reach, threshold) for kind in PATTERNS})


def pii_report(docs: DataFrame) -> DataFrame:
    """One row per document: counts of base spans, digest of base spans, all spans and their scores as text."""
    found = find_pii(docs.select("doc_id", "text"))
    joined = lambda kinds: F.array_join(F.transform(F.concat(*[F.col(f"__{k}") for k in kinds]), lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")
    return found.select(
        "doc_id", *[F.size(f"__{k}").cast("long").alias(f"n_{k}") for k in BASE], F.sha2(joined(BASE), 256).alias("base_sha256"), joined(PATTERNS).alias("spans"),
        F.array_join(F.transform(F.concat(*[F.col(f"__{k}") for k in PATTERNS]), lambda x: x["score"].cast("string")), ",").alias("scores"),
    )


def mask_pii(docs: DataFrame, mark: str = "#") -> DataFrame:
    """docs with every character of a found span replaced by mark."""
    found = find_pii(docs)
    spans = F.concat(*[F.col(f"__{k}") for k in PATTERNS])
    masked = F.aggregate(spans, whole("text"), lambda t, x: F.concat(F.substr(t, F.lit(1), x["start"]), F.repeat(F.lit(mark), x["end"] - x["start"]), F.substr(t, x["end"] + 1)))
    return found.withColumn("__masked", F.when(F.size(spans) > 0, masked).otherwise(F.col("text"))).select(*[F.col("__masked").alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns])
