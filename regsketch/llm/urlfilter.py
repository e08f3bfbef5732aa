"""URL filter: rules first, then a character language-model ratio, in DataFrame operations alone.

URLs that a rule accepts or blocks train two variable-order Markov models of characters:
every order interpolates the next lower one with Witten-Bell weights, down to a uniform
distribution. A URL that no rule fits is judged by the mean log-likelihood difference of
its characters after "://", query and fragment too, against a threshold. That is calibrated on a fifth of the ruled
URLs (by a hash) that the models have not seen; on all of them if a class has none there.

Characters are folded to 31 symbols, so there are at most 32**4 runs of four, however
many URLs there are; the table of ratios is bounded by that.

Defined results: a null URL or one without "://" has empty host and path, fits no rule
and, having no characters to judge, is allowed; a class without training URLs leaves
all else allowed; repeated URLs count as often as they occur; an empty table gives no rows;
other columns pass through.
"""

from __future__ import annotations

from dataclasses import dataclass
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import cut

#: Runs of this many characters: one with its context of up to three.
ORDER = 4
#: Symbols after folding (letters, digits as one, dot, hyphen, slash, underscore, others as one) and the start mark.
SYMBOLS = 32


@dataclass(frozen=True)
class Rule:
    """``allow`` or block what is on ``host`` or its subdomains with a path that begins with ``path``."""

    host: str
    path: str
    allow: bool

    @property
    def text(self) -> str:
        return f"{self.host}{self.path}"


#: Fixed values.
RULES = (Rule("org", "/", True), Rule("example.org", "/es/", False), Rule("example.org", "/en/1", False), Rule("com", "/fr/", True), Rule("com", "/de/", False))

_SPLIT = r"(?s)^.*?://([^/?#]*)([^?#]*)(.*)$"
#: One in so many ruled URLs is kept from the models for calibration.
HELD = 5


def parsed(pages: DataFrame) -> DataFrame:
    """The rows with host (A-Z lower-cased) and path, empty where there is no "://", and with all that follows it over the small alphabet (_body)."""
    url = F.coalesce(F.col("url").cast("string"), F.lit(""))
    host = F.regexp_extract(url, _SPLIT, 1)
    whole = F.concat(*(F.regexp_extract(url, _SPLIT, k) for k in (1, 2, 3)))
    return pages.withColumns({"host": F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), "path": F.regexp_extract(url, _SPLIT, 2), "_body": folded(whole)})


def ruled(pages: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The rows with rule (the longest that fits, or null) and rule_allows."""
    hit = F.lit(None).cast("struct<rule:string,allow:boolean>")
    for rule in sorted(rules, key=lambda r: len(r.text)):  # later ones are longer and win
        fits: Column = ((F.col("host") == rule.host) | F.endswith("host", F.lit(f".{rule.host}"))) & F.startswith("path", F.lit(rule.path))
        hit = F.when(fits, F.struct(F.lit(rule.text).alias("rule"), F.lit(rule.allow).alias("allow"))).otherwise(hit)
    return pages.withColumn("_hit", hit).withColumns({"rule": F.col("_hit.rule"), "rule_allows": F.col("_hit.allow")}).drop("_hit")


def folded(text: Column) -> Column:
    """Text over the small alphabet."""
    return F.regexp_replace(F.regexp_replace(F.lower(text), "[0-9]", "0"), "[^a-z0._/-]", "?")


def _runs(units: DataFrame, *columns: str) -> DataFrame:
    """Each character of ``body`` with the three before it."""
    marked = F.concat(F.lit("^" * (ORDER - 1)), F.col("body"))
    grams = F.transform(F.sequence(F.lit(1), F.length("body")), lambda i: marked.substr(i, F.lit(ORDER)))
    return units.where(F.length("body") > 0).select(*columns, F.explode(grams).alias("gram"))


def ratios(units: DataFrame) -> DataFrame:
    """(gram, ratio) for every run of four characters in ``units`` (body, accepted, rejected): the log of the models' probabilities' ratio."""
    counts = cut(_runs(units, "accepted", "rejected").groupBy("gram").agg(F.sum("accepted").alias("a"), F.sum("rejected").alias("r")))
    lower = None
    for k in range(1, ORDER + 1):
        tail = F.substring("gram", ORDER + 1 - k, k)
        level = counts.groupBy(tail.alias("g")).agg(F.sum("a").alias("a"), F.sum("r").alias("r"))
        context = level.groupBy(F.substring("g", 1, k - 1).alias("c")).agg(*(x for n in "ar" for x in (F.sum(n).alias(f"n{n}"), F.sum((F.col(n) > 0).cast("bigint")).alias(f"t{n}"))))
        known = level.withColumn("c", F.substring("g", 1, k - 1)).join(context, "c")
        if lower is None:
            known = known.withColumns({"qa": F.lit(1.0 / SYMBOLS), "qr": F.lit(1.0 / SYMBOLS)})
        else:
            known = known.withColumn("s", F.substring("g", 2, k - 1)).join(lower.select(F.col("g").alias("s"), F.col("pa").alias("qa"), F.col("pr").alias("qr")), "s")
        smooth = {f"p{n}": F.when(F.col(f"n{n}") > 0, (F.col(n) + F.col(f"t{n}") * F.col(f"q{n}")) / (F.col(f"n{n}") + F.col(f"t{n}"))).otherwise(F.col(f"q{n}")) for n in "ar"}
        lower = known.withColumns(smooth).select("g", "pa", "pr")
    return cut(lower.select(F.col("g").alias("gram"), (F.log("pa") - F.log("pr")).alias("ratio")))


def scores(units: DataFrame, table: DataFrame) -> DataFrame:
    """(body, score): the mean ratio over the characters; the table has at most SYMBOLS ** ORDER rows, so it is broadcast."""
    return _runs(units, "body").join(F.broadcast(table), "gram").groupBy("body").agg(F.avg("ratio").alias("score"))


def scored_units(known: DataFrame) -> DataFrame:
    """(body, accepted, rejected, held, score) for every different body of ``known`` (_body, rule_allows) that is not empty; held ones are not in the models."""
    weights = {"accepted": F.sum(F.coalesce(F.col("rule_allows").cast("bigint"), F.lit(0))), "rejected": F.sum(F.coalesce((~F.col("rule_allows")).cast("bigint"), F.lit(0)))}
    units = known.where("_body <> ''").groupBy(F.col("_body").alias("body")).agg(*(w.alias(k) for k, w in weights.items()))
    held = F.conv(F.substring(F.md5("body"), 1, 4), 16, 10).cast("int") % HELD == 0
    units = cut(units.withColumn("held", held))
    seen = units.select("body", *(F.when(F.col("held"), 0).otherwise(F.col(c)).alias(c) for c in weights))
    return cut(units.join(scores(units, ratios(seen)), "body"))


def threshold(scored: DataFrame) -> float | None:
    """The score between the classes' means, as far from each in its standard deviations; None where a class is empty."""
    weigh = lambda n: (F.sum(n).alias(f"{n}_n"), F.sum(F.col(n) * F.col("score")).alias(f"{n}_1"), F.sum(F.col(n) * F.col("score") * F.col("score")).alias(f"{n}_2"))
    row = scored.agg(*weigh("accepted"), *weigh("rejected")).first()
    of = {}
    for n in ("accepted", "rejected"):
        if not row[f"{n}_n"]:
            return None
        mean = row[f"{n}_1"] / row[f"{n}_n"]
        of[n] = mean, max(1e-6, row[f"{n}_2"] / row[f"{n}_n"] - mean * mean) ** 0.5
    (up, su), (down, sd) = of["accepted"], of["rejected"]
    return (up * sd + down * su) / (su + sd)


def judged(pages: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The rows with host, path, rule, verdict and lm_score (null where a rule decides or there is nothing to judge)."""
    known = ruled(parsed(pages), rules)
    units = scored_units(known)
    least = threshold(units.where("held"))
    least = threshold(units) if least is None else least
    free = units.where("accepted = 0 and rejected = 0").select(F.col("body").alias("_body"), F.col("score").alias("lm_score"))
    # Ruled rows and those without a body seek no score, so that they are in no bucket of the join.
    sought = F.when(F.col("rule_allows").isNull() & (F.col("_body") != ""), F.col("_body"))
    out = known.withColumn("_body", sought).join(free, "_body", "left").drop("_body")
    by_model = F.when(F.col("lm_score") < F.lit(least), "block").otherwise("allow") if least is not None else F.lit("allow")
    return out.withColumn("verdict", F.when(F.col("rule_allows"), "allow").when(~F.col("rule_allows"), "block").otherwise(by_model)).drop("rule_allows")
