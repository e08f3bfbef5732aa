"""Personal data by pattern, checksum and context, in Spark expressions alone.

A pattern proposes spans; a validator (octet range, Luhn, mod-97, digit count) confirms
them; words shortly before raise or lower the score. Spans of the base kinds stay
whatever their score; those of the further kinds stay from ``THRESHOLD`` on, and
where they overlap neither a base span nor one of a kind listed before. Two of these find
what a base pattern loses by running on into digits that follow. Offsets are code points, end exclusive.

Defined results: a null or empty text has no spans; a match that fails validation is
dropped and not retried from within; every row is judged by itself, so repeated rows
give repeated results and an empty table none; other columns pass through.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import free

THRESHOLD = 0.5
#: Code points before a span in which context words count.
CONTEXT = 48


def _digits(match: Column) -> Column:
    return F.regexp_replace(match, "[^0-9]", "")


def octets(match: Column) -> Column:
    """Whether all parts between dots are numbers up to 255."""

    def fits(part: Column) -> Column:
        plain = F.regexp_replace(part, "^0+", "")
        return F.when(F.length(plain) > 3, F.lit(False)).otherwise(F.concat(F.lit("0"), plain).cast("int") <= 255)

    return F.forall(F.split(match, "\\."), fits)


def luhn(digits: Column) -> Column:
    """The Luhn check of a string of digits."""

    def step(total: Column, place: Column) -> Column:
        digit = digits.substr(F.length(digits) - place, F.lit(1)).cast("int")
        twice = digit * (1 + place % 2)
        return total + F.when(twice > 9, twice - 9).otherwise(twice)

    return F.aggregate(F.sequence(F.lit(0), F.length(digits) - 1), F.lit(0), step) % 10 == 0


def mod97(code: Column) -> Column:
    """The check of an international account number: four characters moved to the end, letters as 10 to 35, remainder 1."""
    plain = F.regexp_replace(code, " ", "")
    turned = F.concat(plain.substr(F.lit(5), F.length(plain)), F.substring(plain, 1, 4))

    def step(rest: Column, place: Column) -> Column:
        c = turned.substr(place, F.lit(1))
        value = F.when(F.ascii(c) >= 65, F.ascii(c) - 55).otherwise(F.ascii(c) - 48)
        return (rest * F.when(value > 9, 100).otherwise(10) + value) % 97

    return F.aggregate(F.sequence(F.lit(1), F.length(turned)), F.lit(0), step) == 1


@dataclass(frozen=True)
class Kind:
    """A kind of personal data. ``hint``: a character every match has, if there is one."""

    name: str
    pattern: str
    valid: Callable[[Column], Column]
    base: bool
    prior: float
    hint: str = ""
    raised_by: str = ""


#: Patterns, limits and context words. Possessive repeats and look-behinds
#: keep the matching linear; they match what the plain patterns match.
KINDS = (
    Kind("email", r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", lambda m: F.lit(True), True, 0.9, "@", r"e-?mail|contact|write|mailto|kontakt|schreib|courriel|correo"),
    Kind("ip", r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", octets, True, 0.6, ".", r"\bip\b|address|host|server|login|adresse|serveur|servidor|direcci"),
    Kind("card", r"[0-9](?:[\x20-]?[0-9]){13,}+", lambda m: F.when(F.length(_digits(m)).between(14, 19), luhn(_digits(m))).otherwise(F.lit(False)), True, 0.8, "", r"card|credit|debit|visa|payment|karte|carte|tarjeta|zahlung|paiement|pago"),
    Kind("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: F.length(_digits(m)).between(10, 15), True, 0.7, "+", r"phone|tel|tél|call|mobile|fax|anruf|handy|appel|llama|móvil"),
    Kind("intl_phone", r"\+(?:[0-9]{10,15}|[0-9]{1,3}\x20?(?:\([0-9]{2,4}\)|[0-9]{2,4})[\x20.-][0-9]{3,4}[\x20.-][0-9]{3,4})(?![0-9])", lambda m: F.length(_digits(m)).between(10, 15), False, 0.7, "+", r"phone|tel|tél|call|mobile|fax|anruf|handy|appel|llama|móvil"),
    Kind("plain_card", r"(?<![0-9])(?:[0-9]{14,19}|[0-9]{4}(?:[\x20-][0-9]{4}){3})(?![0-9])", lambda m: luhn(_digits(m)), False, 0.8, "", r"card|credit|debit|visa|payment|karte|carte|tarjeta|zahlung|paiement|pago"),
    Kind("iban", r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]){11,30}+(?![A-Za-z0-9])", mod97, False, 0.9, "", r"iban|account|bank|konto|compte|cuenta"),
    Kind("ssn", r"(?<![0-9A-Za-z-])(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)[0-9]{4}(?![0-9A-Za-z-])", lambda m: F.lit(True), False, 0.3, "-", r"ssn|social security|tax id|sozialversicherung|sécurité sociale|seguridad social"),
    Kind("local_phone", r"(?<![0-9A-Za-z.+-])(?:\([0-9]{3}\)\x20?|[0-9]{3}[.\x20-])[0-9]{3}[.\x20-][0-9]{4}(?![0-9A-Za-z-])", lambda m: F.lit(True), False, 0.3, "", r"phone|tel|tél|call|mobile|fax|whatsapp|anruf|handy|appel|llama|móvil"),
)
RAISE, LOWER = 0.4, 0.4
LOWERED_BY = r"example|order|invoice|sku|isbn|version|serial|ref(erence)?\b|beispiel|bestell|rechnung|exemple|commande|facture|ejemplo|pedido|factura"
BASE = tuple(k.name for k in KINDS if k.base)
SPAN = "array<struct<start:int,rank:int,end:int,kind:string,score:double>>"


def _let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is worked out once, also where lambdas repeat its use."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _folded(items: Column, first: dict[str, Column], step: Callable[[Column, Column], Column], of: str) -> Column:
    """An aggregate over ``items`` that gathers rows (struct type ``of``) in the field ``out`` beside its state, which begins as ``first``; ``step`` returns the next state with ``out`` as an array of the rows to add.

    Rows are gathered by ``CHUNK`` items, and the chunks in an array of arrays, as adding to one array copies it each time.
    """
    rows = f"array<struct<{of}>>"

    def fields(state: Column, out: Column) -> Column:
        return F.struct(*(state[n].alias(n) for n in first), out.alias("out"))

    def inner(state: Column, x: Column) -> Column:
        return _let(step(state, x), lambda after: fields(after, F.concat(state["out"], after["out"])))

    def whole(every: Column) -> Column:
        def outer(state: Column, k: Column) -> Column:
            own = F.aggregate(F.slice(every, k * CHUNK + 1, CHUNK), fields(state, F.array().cast(rows)), inner)
            return _let(own, lambda done: fields(done, F.concat(state["out"], F.array(done["out"]))))

        zero = F.struct(*(c.alias(n) for n, c in first.items()), F.array().cast(f"array<{rows}>").alias("out"))
        chunks = F.sequence(F.lit(0), F.floor((F.size(every) - 1) / CHUNK).cast("int"))
        return F.aggregate(chunks, zero, outer, lambda s: fields(s, F.flatten(s["out"])))

    return _let(items, whole)


#: Items whose rows are gathered in one array before they go to the whole.
CHUNK = 64


def _found(text: Column, matches: Column, kind: Kind, rank: int) -> Column:
    """Spans of the valid matches: pieces between matches and the matches' lengths add up to their places."""
    pieces = F.slice(F.split(text, kind.pattern, -1), F.lit(1), F.size(matches))
    last = lambda s: F.substring(s, -CONTEXT, CONTEXT)

    def step(state: Column, x: Column) -> Column:
        start = state["at"] + F.char_length(x["piece"])
        end = start + F.char_length(x["match"])
        row = lambda before: F.struct(start.alias("start"), end.alias("end"), x["match"].alias("match"), before.alias("before"))
        return _let(last(F.concat(state["tail"], x["piece"])), lambda before: F.struct(end.alias("at"), last(F.concat(before, x["match"])).alias("tail"), F.array(row(before)).alias("out")))

    pairs = F.zip_with(pieces, matches, lambda p, m: F.struct(p.alias("piece"), m.alias("match")))
    placed = _folded(pairs, {"at": F.lit(0), "tail": F.lit("")}, step, "start:int,end:int,match:string,before:string")["out"]

    def scored(x: Column) -> Column:
        before = F.lower(x["before"])
        score = F.lit(kind.prior) + F.when(before.rlike(kind.raised_by), RAISE).otherwise(0.0) - F.when(before.rlike(LOWERED_BY), LOWER).otherwise(0.0)
        return F.struct(x["start"].alias("start"), F.lit(rank).alias("rank"), x["end"].alias("end"), F.lit(kind.name).alias("kind"), F.greatest(F.lit(0.0), F.least(F.lit(1.0), score)).alias("score"))

    return F.transform(F.filter(placed, lambda x: kind.valid(x["match"])), scored)


def detect(docs: DataFrame, kinds: tuple[Kind, ...] = KINDS, threshold: float = THRESHOLD, into: str = "pii_spans") -> DataFrame:
    """The rows with a column of all spans by start, then kind as listed (SPAN); a column of that name is replaced."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    none = F.array().cast("array<string>")
    own = {k.name: free(f"_pii_{k.name}", docs.columns) for k in kinds}
    base, more = (free(n, docs.columns) for n in ("_pii_base", "_pii_more"))
    found = lambda k: F.regexp_extract_all(text, F.lit(k.pattern), F.lit(0))
    matched = docs.withColumns({own[k.name]: F.when(F.instr(text, k.hint) > 0, found(k)).otherwise(none) if k.hint else found(k) for k in kinds})
    empty = F.array().cast(SPAN)
    spans = matched.withColumns({own[k.name]: F.when(F.size(own[k.name]) > 0, _found(text, F.col(own[k.name]), k, rank).cast(SPAN)).otherwise(empty) for rank, k in enumerate(kinds)})
    parts = {base: F.concat(empty, *(F.col(own[k.name]) for k in kinds if k.base)), more: F.concat(empty, *(F.col(own[k.name]) for k in kinds if not k.base))}
    spans = spans.withColumns(parts).drop(*own.values())
    clear = _clear(F.col(base), F.col(more), len(kinds), threshold)
    return spans.withColumn(into, F.sort_array(F.concat(base, F.when(F.size(more) > 0, clear).otherwise(empty)))).drop(base, more)


def digest(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def _clear(base: Column, more: Column, ranks: int, threshold: float) -> Column:
    """Of ``more`` those from the threshold on that overlap no base span and none of a kind listed before; one pass for what begins before a span ends at, and one back."""

    def swept(spans: Column, none: int, blocks: Callable[[Column, Column], Column], edge: Callable[[Column, Column], Column]) -> Column:
        def step(state: Column, x: Column) -> Column:
            counts = x["base"] | (x["score"] >= threshold)
            hit = F.exists(F.slice(state["edge"], F.lit(1), x["rank"]), lambda e: blocks(e, x))
            row = F.struct(*(x[n].alias(n) for n in ("start", "rank", "end", "kind", "score", "base")), (x["free"] & ~hit).alias("free"))
            after = F.transform(state["edge"], lambda e, r: F.when(counts & (r == x["rank"]), edge(e, x)).otherwise(e))
            return F.struct(after.alias("edge"), F.array(row).alias("out"))

        return _folded(spans, {"edge": F.array_repeat(F.lit(none), ranks)}, step, "start:int,rank:int,end:int,kind:string,score:double,base:boolean,free:boolean")["out"]

    marked = lambda spans, is_base: F.transform(spans, lambda x: F.struct(*(x[n].alias(n) for n in ("start", "rank", "end", "kind", "score")), F.lit(is_base).alias("base"), F.lit(True).alias("free")))
    every = F.sort_array(F.concat(marked(base, True), marked(more, False)))
    ahead = swept(every, -1, lambda e, x: e > x["start"], lambda e, x: F.greatest(e, x["end"]))
    back = swept(F.reverse(ahead), (1 << 31) - 1, lambda e, x: e < x["end"], lambda e, x: F.least(e, x["start"]))
    return F.transform(F.filter(back, lambda x: ~x["base"] & x["free"] & (x["score"] >= threshold)), lambda x: F.struct(*(x[n].alias(n) for n in ("start", "rank", "end", "kind", "score"))))


def _replaced(text: Column, spans: Column) -> Column:
    """The text with each span's kind in brackets in its place. Kept pieces are cut out of the stretch of ``CHUNK`` spans they lie in, as a place in a string is found by reading up to it."""

    def step(state: Column, x: Column) -> Column:
        row = F.struct(state["at"].alias("from"), x["start"].alias("upto"), x["kind"].alias("kind"))
        return F.struct(F.greatest(state["at"], x["end"]).alias("at"), F.filter(F.array(row), lambda r: r["from"] <= r["upto"]).alias("out"))

    def chunk(cuts: Column, k: Column) -> Column:
        own = F.slice(cuts, k * CHUNK + 1, CHUNK)
        base = F.get(own, F.lit(0))["from"]
        stretch = text.substr(base + 1, F.element_at(own, -1)["upto"] - base)
        return _let(F.struct(stretch.alias("text"), base.alias("base"), own.alias("own")), lambda c: F.array_join(F.transform(c["own"], lambda r: F.concat(c["text"].substr(r["from"] - c["base"] + 1, r["upto"] - r["from"]), F.lit("["), F.upper(r["kind"]), F.lit("]"))), ""))

    def whole(folded: Column) -> Column:
        cuts = folded["out"]
        chunks = F.sequence(F.lit(0), F.floor((F.size(cuts) - 1) / CHUNK).cast("int"))
        return F.concat(F.array_join(F.transform(chunks, lambda k: chunk(cuts, k)), ""), text.substr(folded["at"] + 1, F.char_length(text)))

    return _let(_folded(spans, {"at": F.lit(0)}, step, "from:int,upto:int,kind:string"), whole)


def mask(docs: DataFrame, kinds: tuple[Kind, ...] = KINDS, threshold: float = THRESHOLD) -> DataFrame:
    """The rows with every span of ``text`` replaced by its kind in brackets, and n_chars, if there, after it; overlapping spans go under the first one's."""
    spans = free("pii_spans", docs.columns)
    text = F.col("text").cast("string")
    masked = detect(docs, kinds, threshold, spans).withColumn("text", F.when(F.size(spans) > 0, _replaced(text, F.col(spans))).otherwise(text))
    if "n_chars" in docs.columns:
        masked = masked.withColumn("n_chars", F.when(F.size(spans) > 0, F.char_length("text")).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType))
    return masked.drop(spans)
