"""Order MinHash fingerprints: sketches of a text that follow its edit distance.

A text is its sequence of words as single spaces part them. Each k-mer of words is numbered by its
occurrence, so repeats differ. Its hash, seeded by that number, puts it into one of m bins; in each bin the
l smallest are selected, put back into the order of the text, and hashed as a tuple. Two
texts agree in a bin if the same k-mers were selected in the same order. DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table

K, BINS, PICKED = 2, 64, 2
#: Low bits of a packed number that hold a k-mer's place in the text; the high bits are its hash.
PLACE_BITS = 27
_PLACE = (1 << PLACE_BITS) - 1
_HEX = 8


def with_fingerprint(df: DataFrame, text: str, name: str, k: int = K, bins: int = BINS, picked: int = PICKED) -> DataFrame:
    """``df`` with the fingerprint of its column ``text``: one number of eight hexadecimal digits for each bin, dots for an empty bin.

    Stages are columns of their own, so that each is computed once. Occurrence numbers come from the
    sorted k-mers: a k-mer equal to its neighbour below looks for the start of its run by halving steps.
    """
    words, s, f = f"{name}_words", f"{name}_sorted", f"{name}_kept"
    shift = PLACE_BITS
    df = df.withColumn(words, F.split(text, " ", -1))
    places = F.sequence(F.lit(0), F.greatest(F.size(words) - k, F.lit(0)))
    packed = F.transform(places, lambda i: F.xxhash64(*(F.get(words, i + j) for j in range(k))).bitwiseAND(F.lit(~_PLACE)).bitwiseOR(i.cast("long")))
    df = df.withColumn(s, F.sort_array(packed))
    same = lambda a, b: F.shiftright(a, shift) == F.shiftright(b, shift)
    steps = F.array(*(F.lit(1 << b) for b in range(PLACE_BITS - 1, -1, -1)))

    def numbered(x: Column, i: Column) -> Column:
        run = F.aggregate(steps, F.lit(0), lambda acc, step: F.when((i - acc - step >= 0) & F.coalesce(same(F.get(F.col(s), i - acc - step), x), F.lit(False)), acc + step).otherwise(acc))
        fresh = F.xxhash64(F.shiftright(x, shift), run).bitwiseAND(F.lit(~_PLACE)).bitwiseOR(x.bitwiseAND(F.lit(_PLACE)))
        return F.when((i > 0) & F.coalesce(same(F.get(F.col(s), i - 1), x), F.lit(False)), fresh).otherwise(x)

    df = df.withColumn(f, F.sort_array(F.transform(F.col(s), numbered)))
    bits = (bins - 1).bit_length()
    bin_of = lambda x: F.shiftrightunsigned(x, 64 - bits)
    low = F.filter(F.col(f), lambda x, i: (i < picked) | (bin_of(F.get(F.col(f), i - picked)) != bin_of(x)))
    df = df.withColumn(f, low)
    place = lambda x: x.bitwiseAND(F.lit(_PLACE))

    def tuple_of(x: Column, i: Column) -> Column:
        mates = F.filter(F.slice(F.col(f), i + 1, picked), lambda y: bin_of(y) == bin_of(x))
        ordered = F.transform(F.array_sort(F.transform(mates, lambda y: F.struct(place(y).alias("p"), y.alias("y")))), lambda t: F.shiftright(t["y"], shift))
        heads = (i == 0) | (bin_of(F.get(F.col(f), i - 1)) != bin_of(x))
        return F.when(heads, F.struct(bin_of(x).alias("b"), F.substring(F.lpad(F.hex(F.xxhash64(ordered)), 16, "0"), 9, _HEX).alias("v")))

    df = df.withColumn(f, F.map_from_entries(F.filter(F.transform(F.col(f), tuple_of), lambda t: t.isNotNull())))
    marks = F.transform(F.sequence(F.lit(0).cast("long"), F.lit(bins - 1).cast("long")), lambda b: F.coalesce(F.try_element_at(F.col(f), b), F.lit("." * _HEX)))
    # A column that is named once would be moved into the lambda and made again for each bin.
    return df.withColumn(name, F.when(F.size(f) >= 0, F.concat_ws("", marks))).drop(words, s, f)


def likeness(a: Column, b: Column, bins: int = BINS) -> Column:
    """Share of agreeing bins among those that either fingerprint fills; 1 for two equal fingerprints."""
    at = lambda c, i: F.substring(c, i * _HEX + 1, F.lit(_HEX))
    empty = F.lit("." * _HEX)
    each = F.sequence(F.lit(0), F.lit(bins - 1))
    used = F.aggregate(each, F.lit(0), lambda n, i: n + F.when((at(a, i) != empty) | (at(b, i) != empty), 1).otherwise(0))
    agree = F.aggregate(each, F.lit(0), lambda n, i: n + F.when((at(a, i) == at(b, i)) & (at(a, i) != empty), 1).otherwise(0))
    return F.when(a == b, 1.0).when(used > 0, agree / used).otherwise(0.0)


def with_next(df: DataFrame, key: str, cols: list[str]) -> DataFrame:
    """``df`` (one partition's worth of rows at a time in order of ``key``) with next_<col> of the following row; the first follows the last.

    Rows are dealt by ranges of the key, whose bounds are keys that occur, so each range's
    first row is known beforehand and is also sent to the range before it. Rows with equal keys stay
    in one range, and ties are ordered by all of ``cols``. Null keys come first.
    """
    spark = df.sparkSession
    parts = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    k = F.coalesce(F.col(key), F.lit(-(1 << 63)))
    facts = df.select(k.alias("k")).agg(F.min("k").alias("low"), F.count(F.lit(1)).alias("n")).first()
    if not facts["n"]:
        return df.withColumns({f"next_{c}": F.col(c) for c in cols})
    parts = max(1, min(max(parts, facts["n"] >> 13), facts["n"]))
    cuts = df.select(k.alias("k")).agg(F.percentile_approx("k", [i / parts for i in range(1, parts)] or [0.5], 10 * parts).alias("q")).first()["q"]
    cuts = sorted({facts["low"], *cuts})
    bounds = F.array(*(F.lit(c).cast("long") for c in cuts))
    halves = F.array(*(F.lit(1 << b) for b in range(max(0, (len(cuts) - 1).bit_length() - 1), -1, -1)))
    reach = F.aggregate(halves, F.lit(0), lambda at, step: F.when(F.coalesce(F.get(bounds, at + step) <= F.col("_key"), F.lit(False)), at + step).otherwise(at))
    rows = df.withColumn("_key", k).withColumn("_part", reach)
    head = F.get(bounds, F.col("_part")) == F.col("_key")
    before = F.pmod(F.col("_part") - 1, F.lit(len(cuts)))
    both = F.array(F.struct(F.col("_part").alias("at"), F.lit(0).alias("ghost")), F.struct(before.alias("at"), F.lit(1).alias("ghost")))
    rows = rows.withColumn("_to", F.explode(F.when(head, both).otherwise(F.slice(both, 1, 1))))
    order = Window.partitionBy("_to.at").orderBy("_to.ghost", "_key", *cols)
    rows = rows.withColumns({f"next_{c}": F.lead(c).over(order) for c in cols})
    return rows.where("_to.ghost = 0").drop("_key", "_part", "_to")


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited text, both fingerprints and their likeness, for each row of ``docs`` (doc_id, text).

    The edited text has its last floor(n_chars / 2) characters replaced by as many of the first of
    the next document's (or all of them). A null text is empty, and an empty text is one empty word. Equal texts have
    equal fingerprints. Repeated doc_ids follow each other in order of their texts; a table of one row is its own next.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    rows = with_next(with_fingerprint(rows, "text", "fingerprint"), "doc_id", ["text", "fingerprint"])
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring("text", F.lit(1), n - half), F.substring("next_text", F.lit(1), half))
    rows = rows.select("doc_id", n.cast("long").alias("n_chars"), edited.alias("edited"), "fingerprint", "next_fingerprint")
    rows = with_fingerprint(rows, "edited", "edited_fingerprint")
    return rows.select(
        "doc_id", "n_chars", "edited", "fingerprint", "edited_fingerprint", likeness(F.col("fingerprint"), F.col("edited_fingerprint")).alias("near_edited"), likeness(F.col("fingerprint"), F.col("next_fingerprint")).alias("near_next")
    )


def op9_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = fingerprints(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_chars", F.sha2(F.encode("edited", "UTF-8"), 256).alias("edited_sha256"), "fingerprint", "edited_fingerprint", "near_edited", "near_next")
