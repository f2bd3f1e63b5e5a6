"""Personal data: patterns propose spans, checksums confirm them, words nearby adjust their score. Native expressions only.

Base kinds are email, ip, card (Luhn) and phone; they stay whatever their score. The method adds iban (ISO 13616 form
in the length of its country, mod-97 equal to 1) and ssn (three-two-four digits, in ranges that are issued), if their score reaches ``THRESHOLD``: a
prior per kind, raised where one of the kind's words stands within ``REACH`` characters before it, lowered where a word of
test data does.

The base patterns are written with possessive repeats and look-behinds, which give the same matches as their plain forms
(stated beside them) without their quadratic backtracking on long runs.

Null and empty texts have no spans. Rows are independent: repeated rows repeat, a null doc_id is returned as it is.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bipercolate.llm.common import let
from bipercolate.llm.spans import count, digest, listed, spans

# Forms of personal data.
EMAIL = r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"  # [A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+
IP = r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"  # [0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)
CARD = r"[0-9](?:[\x20-]?[0-9])++"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
#: Characters of an IBAN by country.
IBAN_LENGTHS = {
    15: "NO", 16: "BE", 18: "DK FI FK FO GL NL SD", 19: "MK SI", 20: "AT BA EE KZ LT LU MN XK", 21: "CH HR LI LV", 22: "BG BH CR DE GB GE IE ME RS VA",
    23: "AE GI IL IQ OM SO TL", 24: "AD CZ ES MD PK RO SA SE SK TN VG", 25: "AO CV GW LY MZ PT ST", 26: "DZ IR IS TR", 27: "BI CF CG CM DJ FR GA GQ GR IT KM MC MG MR SM TD",
    28: "AL AZ BF BJ BY CI CY DO GT HN HU LB MA ML NE NI PL SN SV TG", 29: "BR EG PS QA UA", 30: "JO KW MU YE", 31: "MT SC", 32: "LC", 33: "RU",
}


def _iban(countries: str, length: int) -> str:
    groups, rest = divmod(length - 4, 4)
    return rf"(?:{countries.replace(' ', '|')})[0-9]{{2}}(?:\x20?[A-Z0-9]{{4}}){{{groups}}}" + (rf"\x20?[A-Z0-9]{{{rest}}}" if rest else "")


IBAN = rf"(?<![A-Za-z0-9])(?=[A-Z]{{2}}[0-9]{{2}})(?:{'|'.join(_iban(c, n) for n, c in IBAN_LENGTHS.items())})(?![A-Za-z0-9])"
SSN = r"(?<![0-9-])(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)[0-9]{4}(?![0-9-])"
BASE = ("email", "ip", "card", "phone")
#: Prior scores, and the words that raise them.
PRIOR = {"email": 0.9, "ip": 0.6, "card": 0.8, "phone": 0.6, "iban": 0.7, "ssn": 0.35}
NEARBY = {
    "email": "mail|contact|write to",
    "ip": r"\bip\b|address|host|server",
    "card": "card|credit|visa|payment",
    "phone": "phone|tel|call|fax|mobile",
    "iban": "iban|account|bank|konto|compte|cuenta",
    "ssn": "ssn|social|security|tax",
}
TEST_DATA = "example|sample|dummy|test"
THRESHOLD, REACH, RAISE, LOWER = 0.5, 40, 0.3, 0.3


def _digits(match: Column) -> Column:
    return F.regexp_replace(match, "[^0-9]", "")


def _luhn(match: Column) -> Column:
    """12 to 19 digits whose doubled-alternate sum is a multiple of ten."""
    digits = _digits(match)
    return F.length(digits).between(12, 19) & F.call_function("luhn_check", digits)


def _mod_97(match: Column) -> Column:
    """Letters count as 10 to 35, the first four characters move to the end, the whole number leaves 1."""
    plain = F.regexp_replace(match, "\x20", "")
    turned = F.concat(F.substring(plain, 5, 60), F.substring(plain, 1, 4))
    values = F.transform(F.split(turned, ""), lambda c: F.when(c.rlike("[0-9]"), F.ascii(c) - 48).otherwise(F.ascii(c) - 55))
    rest = F.aggregate(values, F.lit(0), lambda acc, v: F.pmod(acc * F.when(v > 9, 100).otherwise(10) + v, F.lit(97)).cast("int"))
    return F.length(plain).between(15, 34) & (rest == 1)


def _octets(match: Column) -> Column:
    """Four parts of at most 255, however many zeros lead them."""
    return F.forall(F.split(match, r"\."), lambda part: let(F.regexp_replace(part, "^0+(?=.)", ""), lambda p: (F.length(p) <= 3) & (F.lpad(p, 3, "0") <= "255")))


def _phone_digits(match: Column) -> Column:
    return F.length(_digits(match)).between(9, 15)


def candidates(text: Column) -> dict[str, Column]:
    """Spans of each kind that its validator confirms."""
    at, digit = F.contains(text, F.lit("@")), text.rlike("[0-9]")
    found = {
        "email": spans(text, EMAIL, "email", 0, at),
        "ip": F.filter(spans(text, IP, "ip", 1, digit & F.contains(text, F.lit("."))), lambda s: _octets(s["match"])),
        "card": F.filter(spans(text, CARD, "card", 2, digit), lambda s: _luhn(s["match"])),
        "phone": F.filter(spans(text, PHONE, "phone", 3, digit & F.contains(text, F.lit("+"))), lambda s: _phone_digits(s["match"])),
        "iban": F.filter(spans(text, IBAN, "iban", 4, digit), lambda s: _mod_97(s["match"])),
        "ssn": spans(text, SSN, "ssn", 5, digit & F.contains(text, F.lit("-"))),
    }
    return found


def score(text: Column, span: Column, kind: str) -> Column:
    """Prior of the kind, adjusted by the words within REACH characters before the span."""
    first = F.greatest(span["start"] - REACH, F.lit(0))
    around = F.lower(F.substring(text, (first + 1).cast("int"), (span["start"] - first).cast("int")))
    return F.lit(PRIOR[kind]) + F.when(around.rlike(NEARBY[kind]), RAISE).otherwise(0.0) - F.when(around.rlike(TEST_DATA), LOWER).otherwise(0.0)


def confirmed(text: Column, around: Column) -> Column:
    """Sorted spans in ``text``, scored by the words of ``around`` (the same positions); base kinds in any case."""

    def scored(kind: str, found: Column) -> Column:
        rows = F.transform(found, lambda s: F.struct(*[s[x].alias(x) for x in ("start", "rank", "kind", "end", "match")], score(around, s, kind).alias("score")))
        return rows if kind in BASE else F.filter(rows, lambda s: s["score"] >= THRESHOLD)

    return F.array_sort(F.concat(*[scored(kind, found) for kind, found in candidates(text).items()]))


def detect(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with ``pii``, an array of structs start, rank, kind, end, match, score."""
    whole = F.coalesce(F.col(text).cast("string"), F.lit(""))
    return docs.withColumn("pii", confirmed(whole, whole))


def report(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, counts of the base kinds, a digest of their spans, and all spans."""
    found = detect(docs.select("doc_id", "text"))
    base = F.filter("pii", lambda s: s["kind"].isin(*BASE))
    return found.select("doc_id", *[count(F.col("pii"), k).alias(f"n_{k}") for k in BASE], digest(base).alias("base_sha256"), listed(F.col("pii")).alias("spans"), F.size("pii").cast("long").alias("n_spans"))


_PLACE = "struct<start:bigint,end:bigint,kind:string>"


def _places(found: Column) -> Column:
    """Sorted spans as start, end, kind; those that overlap are one, of the first one's kind."""

    def add(acc: Column, s: Column) -> Column:
        last = F.element_at(acc, -1)
        longer = F.struct(last["start"].alias("start"), F.greatest(last["end"], s["end"]).alias("end"), last["kind"].alias("kind"))
        own = F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))
        over = (F.size(acc) > 0) & (F.try_element_at(acc, F.lit(-1))["end"] > s["start"])
        return F.when(over, F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(longer))).otherwise(F.concat(acc, F.array(own)))

    return F.aggregate(found, F.array().cast(f"array<{_PLACE}>"), add)


def _replaced(text: Column, places: Column, mark) -> Column:
    """``text`` with ``mark(place)`` for each of the places, which are sorted and don't overlap."""
    part = lambda first, end: F.substring(text, (first + 1).cast("int"), (end - first).cast("int"))
    zero = F.lit(0).cast("bigint")
    ends = F.concat(F.array(zero), F.transform(places, lambda p: p["end"]))
    pieces = F.zip_with(F.slice(ends, 1, F.size(places)), places, lambda before, p: F.concat(part(before, p["start"]), mark(p)))
    return F.concat(F.array_join(pieces, ""), part(F.element_at(ends, -1), F.length(text)))


def masked_places(text: Column) -> Column:
    """What ``redacted`` masks: the detector's spans, and those it finds once they are covered, until none is left.

    Covered spans keep their length, so that positions and the words nearby stay those of ``text``. A character that no
    pattern knows stands for them, as the brackets of the marks will. Each round but the first finds spans of four digits or more.
    """
    none = F.array().cast(f"array<{_PLACE}>")
    state = lambda covered, places, open_: F.struct(covered.alias("covered"), places.alias("places"), open_.alias("open"))

    def more(at: Column) -> Column:
        def cover(new: Column) -> Column:
            covered = _replaced(at["covered"], new, lambda p: F.repeat(F.lit("]"), (p["end"] - p["start"]).cast("int")))
            return F.when(F.size(new) > 0, state(covered, F.concat(at["places"], new), F.lit(True))).otherwise(state(at["covered"], at["places"], F.lit(False)))

        return let(_places(confirmed(at["covered"], text)), cover)

    rounds = F.sequence(F.lit(1), (F.regexp_count(text, F.lit("[0-9]")) / 4).cast("int") + 2)
    found = F.aggregate(rounds, state(text, none, F.lit(True)), lambda at, _: F.when(at["open"], more(at)).otherwise(at), lambda at: at["places"])
    return F.when(text.rlike("[0-9@]"), F.array_sort(found)).otherwise(none)


def redacted(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with every span that ``detect`` confirms, by its score too, replaced by its kind in brackets.

    Spans that overlap are masked as one. What becomes a span only between masked ones (a phone number before an
    address) is masked too. Null texts stay null.
    """
    plain = F.col(text)
    new = let(masked_places(plain), lambda places: F.when(F.size(places) > 0, _replaced(plain, places, lambda p: F.concat(F.lit("["), F.upper(p["kind"]), F.lit("]")))).otherwise(plain))
    return docs.withColumn(text, F.when(plain.isNotNull(), new))
