"""URL filter: rules, and a character language-model ratio where no rule fits.

Two smoothed Markov models of variable order, one of accepted and one of
rejected URLs, are counted from the URLs on which a rule decides. A context is
used up to the longest one that was seen; the probability of a character under
each order mixes in that of the next shorter context by Witten-Bell smoothing,
down to a uniform distribution. A URL's score is the difference of the two
log-likelihoods divided by its length. The cut between the classes is
calibrated on all ruled URLs: it lies as many standard deviations from either
class's mean. Everything here is DataFrame functions: every gram that a URL has is
scored once, those that no ruled URL has by their shorter contexts, and the table
is joined to the grams of the URLs, by broadcast only where it is counted small.

Defined results: a null URL or one without ``://`` has empty host and path, and
no rule fits it; an empty or null URL is scored by the closing mark alone; with no
ruled URLs of either class every score is 0 and such URLs are allowed; repeated rows are judged
each; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, functions as F

from ..joins import key_join
from ..scratch import materialise

#: Rules as (host, path, verdict); a rule's name is host and path together.
RULES = (
    ("com", "/", "allow"),
    ("example.com", "/en/", "block"),
    ("www.example.com", "/en/", "allow"),
    ("net", "/es/", "block"),
    ("net", "/fr/", "block"),
)

#: Characters of context at most, and the alphabet's size for the uniform distribution.
ORDER = 3
ALPHABET = 96


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host, A-Z in lower case, and path of a URL."""
    url = F.coalesce(url.cast("string"), F.lit(""))
    rest = F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"^[^/?#]*(/[^?#]*)", 1)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """Name and verdict of the longest rule that fits; nulls if none does."""
    name = verdict = F.lit(None).cast("string")
    for rule_host, rule_path, says in sorted(rules, key=lambda r: len(r[0] + r[1])):
        fits = ((host == rule_host) | host.endswith("." + rule_host)) & path.startswith(rule_path)
        name = F.when(fits, F.lit(rule_host + rule_path)).otherwise(name)
        verdict = F.when(fits, F.lit(says)).otherwise(verdict)
    return name, verdict


def _text(url: Column) -> Column:
    """What the models read: the lower-case URL between marks; digits are one character, those outside ASCII another."""
    plain = F.regexp_replace(F.regexp_replace(F.lower(F.coalesce(url.cast("string"), F.lit(""))), "[0-9]", "0"), r"[^\x21-\x7E]", "~")
    return F.concat(F.lit(" " * ORDER), plain, F.lit(" "))


def grams(urls: DataFrame, text: str, order: int = ORDER) -> DataFrame:
    """A row per character after the opening marks: the character with its context of ``order`` characters."""
    return urls.withColumn("gram", F.explode(F.transform(F.sequence(F.lit(1), F.length(text) - order), lambda i: F.substring(F.col(text), i, F.lit(order + 1)))))


def _counts(seen: DataFrame) -> DataFrame:
    """Of each gram of full order that a URL has: how often each class has it."""
    whole = grams(seen.select("says", _text(F.col("url")).alias("text")), "text")
    return whole.groupBy("gram").agg(*[F.count_if(F.col("says") == says).alias(side) for side, says in (("yes", "allow"), ("no", "block"))])


def _steps(full: DataFrame, side: str, k: int) -> tuple[DataFrame, DataFrame]:
    """Of grams with ``k`` characters of context: counts, and each context's total and number of next characters."""
    gram = F.substring("gram", ORDER - k + 1, k + 1)
    own = full.where(F.col(side) > 0).groupBy(gram.alias(f"g{k}")).agg(F.sum(side).alias(f"c{k}"))
    context = own.groupBy(F.substring(f"g{k}", 1, k).alias(f"h{k}")).agg(F.sum(f"c{k}").alias(f"n{k}"), F.count(F.lit(1)).alias(f"t{k}"))
    return own, context


def model(seen: DataFrame) -> DataFrame:
    """Score of each gram of full order that a URL has: log probability accepted less rejected.

    ``seen`` has ``url`` and ``says``, which is null for URLs that teach nothing.
    """
    full = materialise(_counts(seen), "url-grams")
    scored = full.select("gram")
    for side in ("yes", "no"):
        p = F.lit(1.0 / ALPHABET)
        for k in range(ORDER + 1):
            own, context = _steps(full, side, k)
            scored = scored.withColumn(f"g{k}", F.substring("gram", ORDER - k + 1, k + 1)).withColumn(f"h{k}", F.substring("gram", ORDER - k + 1, k))
            scored = scored.join(own, f"g{k}", "left").join(context, f"h{k}", "left")
            mixed = (F.coalesce(f"c{k}", F.lit(0)) + F.col(f"t{k}") * p) / (F.col(f"n{k}") + F.col(f"t{k}"))
            scored = scored.withColumn("p", F.when(F.col(f"n{k}").isNull(), p).otherwise(mixed))
            scored = scored.select("gram", *[c for c in ("l_yes",) if c in scored.columns], "p")
            p = F.col("p")
        scored = scored.withColumn(f"l_{side}", F.ln("p")).drop("p")
    return scored.select("gram", (F.col("l_yes") - F.col("l_no")).alias("score"))


def score(urls: DataFrame, table: DataFrame) -> DataFrame:
    """``urls`` (with ``row_id`` and ``url``) and the difference of their log-likelihoods a character."""
    whole = grams(urls.select("row_id", _text(F.col("url")).alias("text")), "text")
    return key_join(whole, table, ["gram"], "inner").groupBy("row_id").agg((F.sum("score") / F.count(F.lit(1))).alias("lm_score"))


def judge(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", rules=RULES) -> DataFrame:
    """Host, path, rule, verdict and the models' score of every URL."""
    host, path = host_and_path(F.col("url"))
    rule, verdict = rule_of(F.col("host"), F.col("path"), rules)
    seen = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).cast("string").alias("url")).withColumn("row_id", F.monotonically_increasing_id())
    seen = materialise(seen.withColumn("host", host).withColumn("path", path).withColumn("rule", rule).withColumn("says", verdict), "urls")
    table = materialise(model(seen), "url-model")
    # Twice used: for the cut and for the verdicts.
    scored = materialise(seen.join(score(seen, table), "row_id", "left").withColumn("lm_score", F.coalesce(F.round("lm_score", 9), F.lit(0.0))), "url-scores")
    of = scored.where(F.col("says").isNotNull()).groupBy("says").agg(F.avg("lm_score").alias("mean"), F.stddev_pop("lm_score").alias("sd")).collect()
    by = {r["says"]: (r["mean"], r["sd"] or 0.0) for r in of}
    cut = -math.inf
    if len(by) == 2:
        (up, up_sd), (low, low_sd) = by["allow"], by["block"]
        cut = (up * low_sd + low * up_sd) / (up_sd + low_sd) if up_sd + low_sd else (up + low) / 2
    learned = F.when(F.col("lm_score") >= F.lit(cut), "allow").otherwise("block")
    return scored.select("page_id", "host", "path", "rule", F.coalesce("says", learned).alias("verdict"), "lm_score", F.lit(cut).alias("cut"))
