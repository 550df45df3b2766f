"""URL filter: host and path rules, and character language models where no rule fits.

Two variable-order Markov models with Witten-Bell smoothing are counted over all URLs that
rules accept or reject. A URL's log-likelihood difference for each character is held against
a threshold that is calibrated on a fifth of those URLs, which the counts leave out.
DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, written

RULES = (("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/"))
#: Characters in the longest gram: contexts of up to one less.
ORDER = 5
ALPHABET = 256
PAD, END = "\u0002", "\u0003"
BINS_A_NAT, MOST_BINS = 32, 256
#: Gram tables of up to so many rows are broadcast; longer ones are joined by shuffle.
BROADCAST_GRAMS = 200_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column) -> tuple[Column, Column]:
    rest = F.when(F.instr(url, "://") > 0, F.substring_index(F.concat(F.lit("x"), url), "://", 1))
    rest = F.when(rest.isNotNull(), F.substring(url, F.length(rest) + 3, F.length(url)))
    host = F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), UPPER, LOWER)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def matched_rule(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """(rule, verdict): of the rules that fit, the longest; null if none does."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, text in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        name, _, rest = text.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith("/" + rest)
        rule, verdict = F.when(fits, text).otherwise(rule), F.when(fits, kind).otherwise(verdict)
    return rule, verdict


def _grams(texts: DataFrame) -> DataFrame:
    """The columns of ``texts`` with each gram of its column s."""
    padded = F.concat(F.lit(PAD * (ORDER - 1)), F.col("s"), F.lit(END))
    return texts.withColumn("g", F.explode(F.transform(F.sequence(F.lit(1), F.length("s") + 1), lambda i: F.substring(padded, i, F.lit(ORDER)))))


def gram_scores(grams: DataFrame) -> DataFrame:
    """g, gain: log-likelihood of each gram's last character if accepted, less that if rejected.

    ``grams`` has each gram once, with its counts a (accepted) and r (rejected), which may be 0.
    """
    levels = [grams]
    for n in range(ORDER - 1, 0, -1):
        levels.append(levels[-1].groupBy(F.expr(f"right(g, {n})").alias("g")).agg(F.sum("a").alias("a"), F.sum("r").alias("r")))
    known = None
    for n, level in enumerate(reversed(levels), 1):
        context = F.expr(f"left(g, {n - 1})").alias("context")
        kinds = [F.count_if(F.col(c) > 0).alias(f"kinds_{c}") for c in "ar"]
        seen = level.groupBy(context).agg(*(F.sum(c).alias(f"all_{c}") for c in "ar"), *kinds)
        rows = level.withColumn("context", context).join(seen, "context")
        if known is None:
            rows = rows.withColumns({f"low_{c}": F.lit(1 / ALPHABET) for c in "ar"})
        else:
            rows = rows.withColumn("shorter", F.expr(f"right(g, {n - 1})")).join(known, "shorter")
        smooth = {c: F.when(F.col(f"all_{c}") > 0, (F.col(c) + F.col(f"kinds_{c}") * F.col(f"low_{c}")) / (F.col(f"all_{c}") + F.col(f"kinds_{c}"))).otherwise(F.col(f"low_{c}")) for c in "ar"}
        known = rows.select(F.col("g").alias("shorter"), *(smooth[c].alias(f"low_{c}") for c in "ar"))
    return known.select(F.col("shorter").alias("g"), (F.log("low_a") - F.log("low_r")).alias("gain"))


def judged_urls(pages: DataFrame, rules=RULES) -> DataFrame:
    """page_id, host, path, rule, verdict, score for each row of ``pages`` (page_id, url).

    A null url, or one without ``://``, has an empty host and path and is scored as the empty text.
    Without URLs of both kinds to learn from, the models allow everything. Repeated rows are
    judged alike. An empty table gives no rows. The score is null where a rule decides.
    """
    host, path = host_and_path(F.col("url"))
    rows = pages.select("page_id", host.alias("host"), path.alias("path"))
    rule, ruled = matched_rule(F.col("host"), F.col("path"), rules)
    rows = rows.select("page_id", "host", "path", rule.alias("rule"), ruled.alias("ruled"), F.concat("host", "path").alias("s"))
    kind = rows.groupBy("s").agg(*(F.count_if(F.col("ruled") == v).alias(c) for v, c in (("allow", "a"), ("block", "r"))), F.count_if(F.col("ruled").isNull()).alias("open"))
    kind = written(kind.withColumn("test", F.pmod(F.xxhash64("s"), F.lit(5)) == 0), "urls")
    fit = [F.sum(F.when(F.col("test"), 0).otherwise(F.col(c))).alias(c) for c in "ar"]
    counts = written(_grams(kind.where("open > 0 or test or a + r > 0")).groupBy("g").agg(*fit), "grams")
    total = counts.agg(F.sum("a").alias("a"), F.sum("r").alias("r"), F.count(F.lit(1)).alias("n")).first()
    gain = written(gram_scores(counts), "gains")
    gain = F.broadcast(gain) if total["n"] <= BROADCAST_GRAMS else gain
    scored = _grams(kind.where("open > 0 or test").select("s", "a", "r")).join(gain, "g").groupBy("s").agg(F.avg("gain").alias("score"), F.max("a").alias("a"), F.max("r").alias("r"))
    scored = written(scored, "scores")
    least = threshold(scored) if total["a"] and total["r"] else None
    out = rows.join(scored.select("s", "score"), "s", "left")
    own = F.when(F.lit(least is None) | (F.col("score") >= F.lit(least or 0.0)), "allow").otherwise("block")
    return out.select("page_id", "host", "path", "rule", F.coalesce("ruled", own).alias("verdict"), F.when(F.col("ruled").isNull(), F.col("score")).alias("score"))


def threshold(scored: DataFrame) -> float | None:
    """The score that best parts held-out accepted from rejected URLs, by the mean of both shares caught."""
    place = F.least(F.greatest(F.floor(F.col("score") * BINS_A_NAT), F.lit(-MOST_BINS)), F.lit(MOST_BINS))
    bins = scored.groupBy(place.alias("bin")).agg(F.sum("a").alias("a"), F.sum("r").alias("r")).orderBy("bin").collect()
    all_a, all_r = sum(b["a"] for b in bins), sum(b["r"] for b in bins)
    if not all_a or not all_r:
        return None
    best, at, below_a, below_r = 1.0, -float(MOST_BINS), 0, 0
    for b in bins:
        if (got := (all_a - below_a) / all_a + below_r / all_r) > best:
            best, at = got, b["bin"] / BINS_A_NAT
        below_a, below_r = below_a + b["a"], below_r + b["r"]
    return at


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged_urls(table(spark, sf_dir, "pages"))
