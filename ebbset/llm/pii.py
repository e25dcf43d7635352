"""Personal data by patterns, checksums and context, in DataFrame functions only.

Regular expressions propose spans. Validators confirm them: octet range for ip, length and Luhn for card, digit count for
phone, mod-97 for iban. Every proposal has a base score, raised by words nearby that name its kind and lowered by words
before it that name something else. What passes a base rule stays whatever its context; what the method adds (iban, identity
numbers, local phone numbers) must be confirmed by checksum or context, its score reaching the threshold.

The patterns give what the plain ones give but can't backtrack: runs are possessive and a search doesn't begin inside a
run it has already tried. Matches are folded in runs, which keeps their cost down but not linear: each run begins by
adding up the lengths before it, and copies what it found. The place of a match comes from the
lengths of what lies between matches, so positions count code points.

Defined results: null text counts as empty and has no spans; equal rows give equal results; rows are independent;
other columns pass through untouched, whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Code points of context looked at before and after a match.
BEFORE, AFTER = 48, 16
THRESHOLD = 0.6
RUN = 64
SPANS = "array<struct<start:int,rank:int,kind:string,end:int,score:double,base:boolean>>"
NUMBERS = "[0-9][ .-]?[0-9]"


@dataclass(frozen=True)
class Kind:
    """A kind of span: what a text must hold at all, its pattern, score and context words, whether a base rule."""

    name: str
    needs: str
    pattern: str
    score: float
    near: str
    base: bool


PHONE_WORDS = r"phone|tel|call|mobil|fax|movil|móvil|portable"
KINDS = (
    Kind("email", "@", r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", 0.9, r"mail|contact|kontakt|correo|courriel", True),
    Kind("ip", NUMBERS, r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", 0.7, r"\bip\b|address|host|server|adres", True),
    Kind("card", NUMBERS, r"[0-9](?:[ -]?[0-9])++", 0.8, r"card|visa|credit|karte|tarjeta|carte", True),
    Kind("phone", "+", r"\+[0-9][ ().0-9-]+[0-9]", 0.7, PHONE_WORDS, True),
    Kind("iban", "[A-Z]{2}[0-9]{2}", r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}+(?: ?[A-Z0-9]{1,3})?+(?![A-Za-z0-9])", 0.7, r"iban|konto|account|bank|cuenta|compte", False),
    Kind("id_number", NUMBERS, r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])", 0.4, r"ssn|social|security|sozial|seguridad|sécurité", False),
    Kind("local_phone", NUMBERS, r"(?<![0-9+(-])(?:\([0-9]{3}\) ?|[0-9]{3}[ .-])[0-9]{3}[ .-][0-9]{4}(?![0-9-])", 0.4, PHONE_WORDS, False),
)
#: Words that speak against a kind the method adds.
AGAINST = r"version|isbn|order|invoice|serial|rechnung|factura|facture"


def characters(text: Column) -> Column:
    return F.filter(F.split(text, ""), lambda c: c != "")


def luhn(digits: Column) -> Column:
    """Whether the Luhn sum is a multiple of 10."""
    each = F.transform(characters(F.reverse(digits)), lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise(c.cast("int") * 2 - F.when(c > "4", 9).otherwise(0)))
    return F.aggregate(each, F.lit(0), lambda a, d: a + d) % 10 == 0


def mod97(iban: Column) -> Column:
    """Whether an IBAN without blanks leaves 1: the first four characters go last, letters count from 10 on."""
    moved = F.concat(F.substr(iban, F.lit(5)), F.left(iban, F.lit(4)))
    values = F.transform(characters(moved), lambda c: F.ascii(c) - F.when(c <= "9", 48).otherwise(55))
    return F.aggregate(values, F.lit(0), lambda a, v: (a * F.when(v < 10, 10).otherwise(100) + v) % 97) == 1


def confirmed(kind: Kind, match: Column) -> Column:
    digits = F.regexp_replace(match, "[^0-9]", "")
    if kind.name == "ip":
        return F.forall(F.split(match, r"\."), lambda p: F.regexp_replace(p, "^0+", "").rlike(r"^(?:[0-9]{0,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])$"))
    if kind.name == "card":
        return (F.length(match) < 38) & F.length(digits).between(14, 19) & luhn(digits)
    if kind.name == "phone":
        return F.length(digits).between(10, 15)
    if kind.name == "iban":
        bare = F.replace(match, F.lit(" "), F.lit(""))
        return F.length(bare).between(15, 34) & mod97(bare)
    return F.lit(True)


def _runs(matches: str) -> Column:
    """Numbers of the runs of matches; a run is folded at a time, so that few spans are copied at once."""
    return F.sequence(F.lit(0), F.floor((F.size(matches) - 1) / RUN).cast("int"))


def _run(c: Column, matches: str) -> Column:
    return F.sequence(c * RUN, F.least(c * RUN + RUN, F.size(matches)) - 1)


def _lengths(matches: str, gaps: str) -> Column:
    """Code points of each run of matches with the gaps before them."""
    one = lambda a, i: a + F.char_length(F.get(F.col(gaps), i)) + F.char_length(F.get(F.col(matches), i))
    return F.when(F.size(matches) > RUN, F.transform(_runs(matches), lambda c: F.aggregate(_run(c, matches), F.lit(0), one))).otherwise(F.array(F.lit(0)))


def _spans_of(rank: int, kind: Kind, matches: str, gaps: str, lengths: str) -> Column:
    """The confirmed spans among one kind's matches, given them and what lies around them."""

    def step(acc: Column, i: Column) -> Column:
        match, gap = F.get(F.col(matches), i), F.get(F.col(gaps), i)
        start = acc["at"] + F.char_length(gap)
        end = start + F.char_length(match)
        before = F.lower(F.right(gap, F.lit(BEFORE)))
        near = F.concat(before, F.lit(" "), F.lower(F.left(F.get(F.col(gaps), i + 1), F.lit(AFTER))))
        score = F.lit(kind.score) + F.when(near.rlike(kind.near), 0.3).otherwise(0.0) - F.when(before.rlike(AGAINST), 0.3).otherwise(0.0)
        keep = confirmed(kind, match) & (F.lit(kind.base) | (score >= THRESHOLD))
        one = F.struct(start.alias("start"), F.lit(rank).alias("rank"), F.lit(kind.name).alias("kind"), end.alias("end"), F.least(score, F.lit(1.0)).alias("score"), F.lit(kind.base).alias("base"))
        return F.struct(end.alias("at"), F.when(keep, F.concat(acc["out"], F.array(one))).otherwise(acc["out"]).alias("out"))

    none = F.from_json(F.lit("[]"), SPANS)

    def run(c: Column) -> Column:
        at = F.aggregate(F.slice(F.col(lengths), F.lit(1), c), F.lit(0), lambda a, n: a + n)
        return F.aggregate(_run(c, matches), F.struct(at.alias("at"), none.alias("out")), step, lambda a: a["out"])

    return F.when(F.size(matches) > 0, F.flatten(F.transform(_runs(matches), run))).otherwise(none)


def find(docs: DataFrame, text: str = "text", to: str = "spans") -> DataFrame:
    """Adds an array of spans (start, rank, kind, end, score, base), by start, then kind as listed."""
    names = docs.columns
    own = [f"c{i}" for i in range(len(names))]  # so that no name can clash with those used here
    docs = docs.toDF(*own)
    plain = F.coalesce(F.col(own[[c.lower() for c in names].index(text.lower())]).cast("string"), F.lit(""))
    matches = []
    for r, k in enumerate(KINDS):
        may = F.contains(plain, F.lit(k.needs)) if len(k.needs) == 1 else plain.rlike(k.needs)
        matches.append(F.when(may, F.regexp_extract_all(plain, F.lit(k.pattern), F.lit(0))).otherwise(F.array().cast("array<string>")).alias(f"__m{r}"))
    found = docs.select(*own, *matches)
    gaps = [F.when(F.size(f"__m{r}") > 0, F.split(plain, k.pattern, -1)).alias(f"__g{r}") for r, k in enumerate(KINDS)]
    found = found.select("*", *gaps)
    found = found.select("*", *[_lengths(f"__m{r}", f"__g{r}").alias(f"__l{r}") for r in range(len(KINDS))])
    spans = [_spans_of(r, k, f"__m{r}", f"__g{r}", f"__l{r}") for r, k in enumerate(KINDS)]
    return found.select(*own, F.array_sort(F.concat(*spans)).alias("s")).toDF(*names, to)


def mask(text: Column, spans: Column) -> Column:
    """The text with each maximal run of overlapping spans replaced by the first one's kind in brackets."""

    def step(acc: Column, s: Column) -> Column:
        fresh = s["start"] >= acc["at"]
        more = F.array(F.substr(text, acc["at"] + 1, s["start"] - acc["at"]), F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]")))
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(fresh, F.concat(acc["out"], more)).otherwise(acc["out"]).alias("out"))

    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out"))
    whole = F.aggregate(spans, start, step, lambda a: F.concat(F.array_join(a["out"], ""), F.substr(text, a["at"] + 1)))
    return F.when(F.size(spans) > 0, whole).otherwise(text)


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def _is(name: str):
    return lambda s: s["kind"] == name


def digest(docs: DataFrame) -> DataFrame:
    """Counts and lists of spans per document."""
    found = find(docs.select("doc_id", "text"))
    base = F.filter("spans", lambda s: s["base"])
    counts = [F.size(F.filter("spans", _is(k.name))).cast("long").alias(f"n_{k.name}") for k in KINDS if k.base]
    return found.select("doc_id", *counts, F.sha2(_listed(base), 256).alias("base_sha256"), _listed(F.col("spans")).alias("spans"))
