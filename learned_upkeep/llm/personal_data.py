"""Operator 5, personal data (DataFrame functions only).

Patterns propose spans, validators confirm them (number ranges, Luhn, mod 97), and a score that the
words around a span raise or lower decides about the kinds that have no validator of their own.

Positions come without a scan per character: the pieces between a pattern's matches and the matches
themselves alternate, so running sums of their lengths in code points are the spans.  Every pattern
matches in time linear in the text (possessive runs, entered at their first character only).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import whole_text

#: In the order in which kinds at one start are listed.
BASE_KINDS = ("email", "ip", "card", "phone")
_PART = r"0*(?:25[0-5]|2[0-4][0-9]|1[0-9]{2}|[0-9]{1,2})"
#: Characters of an account number by country, as registered (fixed values).
IBAN_COUNTRIES = {
    15: "NO", 16: "BE", 18: "DK FI FK FO GL NL SD", 19: "MK SI", 20: "AT BA EE KZ LT LU MN XK", 21: "CH HR LI LV", 22: "BG BH CR DE GB GE IE ME RS VA",
    23: "AE GI IL IQ OM SO TL", 24: "AD CZ ES MD PK RO SA SE SK TN VG", 25: "LY PT ST", 26: "IS TR", 27: "BI DJ FR GR IT MC MR SM", 28: "AL AZ BY CY DO GT HU LB NI PL",
    29: "BR EG PS QA UA", 30: "JO KW MU YE", 31: "MT SC", 32: "LC", 33: "RU",
}
_REGISTERED = "(?:" + "|".join(" ".join(IBAN_COUNTRIES.values()).split()) + ")"
_IBAN = "|".join(rf"(?:{c.replace(' ', '|')})[0-9]{{2}}(?:\x20?[A-Z0-9]){{{n - 4}}}(?![A-Za-z0-9])" for n, c in IBAN_COUNTRIES.items())
PATTERNS = {
    # a run of local-part characters is entered at its start, or where the match before has ended
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?+[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    # the length of a registered country; of another one a run up to the next registered number, whose end the checksum finds
    "iban": rf"(?<![A-Za-z0-9])(?:{_IBAN}|(?!{_REGISTERED})[A-Z]{{2}}[0-9]{{2}}(?:(?!\x20{_REGISTERED}[0-9]{{2}})\x20?[A-Z0-9]){{11,30}}(?![A-Za-z0-9]))",
    "local_phone": r"(?<![0-9+.(-])\(?[0-9]{2,4}[).\x20/-]{1,2}[0-9]{3,4}[.\x20-]?[0-9]{3,4}(?![0-9.-])",
    "national_id": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    # a long run with a digit and a letter, entered at its start only
    "secret": r"(?<![A-Za-z0-9+/_-])(?=[A-Za-z+/_-]{0,200}[0-9])(?=[0-9+/_-]{0,200}[A-Za-z])[A-Za-z0-9+/_-]{20,}+",
}
#: A cheap test that a text can hold a kind at all.
_NEEDS = {"email": "@", "phone": "+"}
#: Score before context, and context words (fixed values) that raise it by half when one stands within CONTEXT characters.
_PRIOR = {"iban": 1.0, "local_phone": 0.3, "national_id": 0.3, "secret": 0.3}
CONTEXT_WORDS = {
    "iban": ("iban", "account", "konto", "compte", "cuenta"),
    "local_phone": ("phone", "telephone", "tel", "call", "mobile", "telefon", "téléphone", "teléfono"),
    "secret": ("token", "secret", "password", "passwd", "api key", "api_key", "apikey", "access key", "private key", "bearer", "credential", "credentials"),
    "national_id": ("ssn", "social security", "national id", "ausweis", "sécurité sociale", "dni"),
}
#: Words that speak against personal data (fixed values); each kind loses half.
_AGAINST = ("version", "license", "isbn", "page", "figure")
CONTEXT = 40
#: Matches in a block.
BLOCK = 128
THRESHOLD = 0.5


def _digits(c: Column) -> Column:
    return F.regexp_replace(c, "[^0-9]", "")


def luhn(number: Column) -> Column:
    """True if the digits in ``number`` satisfy the Luhn checksum."""
    d = F.split(F.reverse(_digits(number)), "")
    worth = F.transform(d, lambda x, i: F.when(i % 2 == 0, x.cast("int")).otherwise(F.element_at(F.array(*[F.lit(v) for v in (0, 2, 4, 6, 8, 1, 3, 5, 7, 9)]), x.cast("int") + 1)))
    return F.aggregate(worth, F.lit(0), lambda a, x: a + x) % 10 == 0


def mod97(iban: Column) -> Column:
    """True if ``iban``, its first four characters moved to the end and letters read as 10 to 35, leaves 1 modulo 97."""
    bare = F.regexp_replace(iban, r"\x20", "")
    turned = F.split(F.concat(F.substring(bare, 5, 64), F.substring(bare, 1, 4)), "")

    def step(a: Column, x: Column) -> Column:
        v = F.ascii(x)
        return F.when(v >= 65, (a * 100 + v - 55) % 97).otherwise((a * 10 + v - 48) % 97)

    return F.aggregate(turned, F.lit(0), step) == 1


def _longest_valid(m: Column) -> Column:
    """The longest head of a proposed account number, cut at a space, that the checksum confirms; null without one."""
    words = F.split(m, r"\x20")
    heads = F.transform(F.sequence(F.size(words), F.lit(1), F.lit(-1)), lambda i: F.array_join(F.slice(words, 1, i), " "))
    valid = F.filter(heads, lambda h: (F.length(F.replace(h, F.lit(" "), F.lit(""))) >= 15) & mod97(h))
    return F.when(m.rlike("^" + _REGISTERED), m).otherwise(F.get(valid, 0))


def _confirmed(kind: str, m: Column, before: Column, after: Column) -> Column:
    n = F.length(_digits(m))
    if kind == "ip":
        return m.rlike(rf"^{_PART}(?:\.{_PART}){{3}}$")
    if kind == "card":
        return F.when(n.between(12, 19), luhn(m)).otherwise(False)
    if kind == "phone":
        return n.between(9, 15)
    if kind in _PRIOR:
        near = F.lower(F.concat(before, F.lit(" "), after))
        word = lambda words: near.rlike(r"(?<!\p{L})(?:" + "|".join(words) + r")(?!\p{L})")
        score = F.lit(_PRIOR[kind]) + F.when(word(CONTEXT_WORDS[kind]), 0.5).otherwise(0.0) - F.when(word(_AGAINST), 0.5).otherwise(0.0)
        valid = {"iban": mod97(m), "local_phone": n.between(8, 12), "national_id": ~m.rlike("^(?:000|666|9)|-00-|0000$"), "secret": F.lit(True)}[kind]
        return valid & (score >= THRESHOLD)
    return F.lit(True)


def spans_of(text: Column, kind: str) -> Column:
    """array<struct<start,kind_no,kind,end>> of one kind's confirmed spans, in code points, end exclusive."""
    no = list(PATTERNS).index(kind)
    pattern = PATTERNS[kind]
    pieces, found = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    # matches with the piece before and after each; zipped whole, as a lambda would cut the text anew for every match
    zipped = F.filter(F.arrays_zip(pieces.alias("piece"), found.alias("m"), F.slice(pieces, 2, F.length(text) + 1).alias("next")), lambda z: z["m"].isNotNull())
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,kind_no:int,kind:string,end:int>>").alias("out"))

    def step(a: Column, x: Column) -> Column:
        begin = a["at"] + F.length(x["piece"])
        end = begin + F.length(x["m"])
        m, after = x["m"], x["next"]
        if kind == "iban":
            m = F.coalesce(_longest_valid(m), m)
            after = F.concat(F.substring(x["m"], F.length(m) + 1, F.length(x["m"])), after)
        span = F.struct(begin.alias("start"), F.lit(no).alias("kind_no"), F.lit(kind).alias("kind"), (begin + F.length(m)).alias("end"))
        ok = _confirmed(kind, m, F.substring(x["piece"], -CONTEXT, CONTEXT), F.substring(after, 1, CONTEXT))
        return F.struct(end.alias("at"), F.when(ok, F.array_append(a["out"], span)).otherwise(a["out"]).alias("out"))

    none = start["out"]
    nested = F.struct(F.lit(0).alias("at"), F.array().cast("array<array<struct<start:int,kind_no:int,kind:string,end:int>>>").alias("out"))

    def block(a: Column, part: Column) -> Column:
        return F.aggregate(part, F.struct(a["at"].alias("at"), none.alias("out")), step, lambda b: F.struct(b["at"].alias("at"), F.array_append(a["out"], b["out"]).alias("out")))

    # appending copies a list, so matches go through in blocks and only whole blocks are appended to the long one
    cut = lambda z: F.transform(F.sequence(F.lit(0), F.floor(F.size(z) / BLOCK).cast("int")), lambda b: F.slice(z, b * BLOCK + 1, BLOCK))
    spans = F.get(F.transform(F.array(zipped), lambda z: F.aggregate(cut(z), nested, block, lambda a: F.flatten(a["out"]))), 0)
    return F.when(text.contains(_NEEDS[kind]), spans).otherwise(none) if kind in _NEEDS else spans


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def personal_data(docs: DataFrame, extra: bool = True) -> DataFrame:
    """One row per input row: doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_spans.

    A null or empty text has no spans (spans is then the empty string).  Spans of different kinds may
    overlap; those of one kind never do.  Repeated rows are answered each; an empty table gives an
    empty result; further columns are ignored.  With ``extra`` the kinds beyond the base are added:
    iban (mod 97), and local_phone, national_id and secret (keys and tokens) where a word nearby supports them.
    """
    text = F.col("__text")
    kinds = list(PATTERNS) if extra else list(BASE_KINDS)
    base = docs.select("doc_id", whole_text().alias("__text"))
    # texts without a digit or an at sign hold nothing of any kind, and skip all patterns
    may = text.rlike("[0-9@]")
    none = F.array().cast("array<struct<start:int,kind_no:int,kind:string,end:int>>")
    found = base.select("doc_id", *[F.when(may, spans_of(text, k)).otherwise(none).alias(f"__{k}") for k in kinds])
    own = F.array_sort(F.flatten(F.array(*[F.col(f"__{k}") for k in BASE_KINDS])))
    everything = F.array_sort(F.flatten(F.array(*[F.col(f"__{k}") for k in kinds])))
    return found.select(
        "doc_id", *[F.size(f"__{k}").cast("long").alias(f"n_{k}") for k in BASE_KINDS],
        F.sha2(_listed(own), 256).alias("base_sha256"), _listed(everything).alias("spans"), F.size(everything).cast("long").alias("n_spans"),
    )


def redacted(docs: DataFrame, extra: bool = True) -> DataFrame:
    """``docs`` with every confirmed span replaced by its kind in brackets; overlapping spans become one."""
    text = whole_text()
    kinds = list(PATTERNS) if extra else list(BASE_KINDS)
    spans = F.array_sort(F.flatten(F.array(*[spans_of(text, k) for k in kinds])))
    begin = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(a: Column, s: Column) -> Column:
        kept = F.concat(a["out"], F.substring(text, a["at"] + 1, s["start"] - a["at"]), F.lit("["), s["kind"], F.lit("]"))
        return F.when(s["start"] >= a["at"], F.struct(s["end"].alias("at"), kept.alias("out"))).otherwise(F.struct(F.greatest(a["at"], s["end"]).alias("at"), a["out"].alias("out")))

    return docs.withColumn("text", F.aggregate(spans, begin, step, lambda a: F.concat(a["out"], F.substring(text, a["at"] + 1, F.length(text)))))
