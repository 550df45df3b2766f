"""Noisy multilingual text: repair, masks, idioms, protected stop words, lemmas, encoders, duplicates."""

from __future__ import annotations

import re
import unicodedata
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Word lists and patterns.
HTML_TAG = "<[A-Za-z/!][^>]*>"
URL = "(https?://|www[.])[^ \"<>]+"
EMAIL = "[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+[.][A-Za-z]+"
IDIOMS = {"esta chido": "es bueno", "muy canon": "muy dificil", "padre": "bueno", "gacho": "malo"}
STOP = ("de", "la", "que", "el", "en", "y", "a", "los", "se", "del", "las", "un", "por", "con", "no", "una", "su", "para", "es", "al", "lo", "como", "mas", "pero", "sus", "le", "ya", "o", "fue", "muy")
PROTECTED = ("no", "nunca", "jamás", "ni", "sin", "muy", "poco", "tan")
LEMMAS = {"comimos": "comer", "comiendo": "comer", "comeremos": "comer", "buenos": "bueno", "buena": "bueno", "malas": "malo", "fue": "ser", "era": "ser", "hoteles": "hotel"}
EMOJI_NAMES = {0x1F44D: "thumbs_up", 0x2764: "red_heart"}
MOJIBAKE = "[ÃÂâ]"
EMOJI = "[\\x{1F300}-\\x{1FAFF}\\x{2600}-\\x{27BF}]"
SPACE = "[ \\t\\n\\r]+"


def repair_text(text: str) -> str:
    """Text whose UTF-8 was read as a one-byte code, put right; other text unchanged. Doing it twice changes nothing more."""
    junk = len(re.findall(MOJIBAKE, text))
    for code in ("cp1252", "latin-1"):
        try:
            fixed = text.encode(code).decode("utf-8")
        except UnicodeError:
            continue
        if len(re.findall(MOJIBAKE, fixed)) < junk:
            return fixed
    return text


def demojize_text(text: str) -> str:
    out = []
    for c in text:
        p = ord(c)
        if p == 0xFE0F:
            continue
        if 0x1F300 <= p <= 0x1FAFF or 0x2600 <= p <= 0x27BF:
            name = EMOJI_NAMES.get(p) or unicodedata.name(c, f"u{p:x}").lower().replace(" ", "_")
            out.append(f":{name}:")
        else:
            out.append(c)
    return "".join(out)


def _series(f):
    def run(frames: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in frames:
            yield s.map(f, na_action="ignore")

    return F.pandas_udf(run, "string")


#: Steps on characters, each with what a text must have to be changed by it. ASCII text is changed by none.
CHARACTER_STEPS = {"repair": (MOJIBAKE, repair_text), "nfkc": ("[^\\x00-\\x7F]", lambda t: unicodedata.normalize("NFKC", t)), "demojize": ("[\U0001f300-\U0001faff\u2600-\u27bf]", demojize_text)}


def characters(c: Column, steps: tuple[str, ...]) -> Column:
    """Several steps on characters in one Python worker; a chain of functions would have one a step."""
    does = [(re.compile(CHARACTER_STEPS[name][0]), CHARACTER_STEPS[name][1]) for name in steps]

    def run(t):
        for pattern, f in does:
            if pattern.search(t):
                t = f(t)
        return t

    return F.when(c.rlike("[^\\x00-\\x7F]"), _series(run)(c)).otherwise(c) if steps else c


def repair(c: Column) -> Column:
    return F.when(c.rlike(MOJIBAKE), _series(repair_text)(c)).otherwise(c)


def nfkc(c: Column) -> Column:
    return F.when(c.rlike("[^\\x00-\\x7F]"), _series(lambda t: unicodedata.normalize("NFKC", t))(c)).otherwise(c)


def demojize(c: Column) -> Column:
    return F.when(c.rlike(EMOJI), _series(demojize_text)(c)).otherwise(c)


def mask(c: Column) -> Column:
    """Tags, links and addresses to one token each; a link inside a tag goes with it."""
    return F.regexp_replace(F.regexp_replace(F.regexp_replace(c, HTML_TAG, "[HTML]"), URL, "[URL]"), EMAIL, "[EMAIL]")


def normalize_idioms(c: Column, idioms: dict[str, str] = IDIOMS) -> Column:
    """Whole phrases only, the longest first, in any case; a space in a phrase is also an underscore."""
    for phrase in sorted(idioms, key=lambda p: (-len(p), p)):
        c = F.regexp_replace(c, f"(?i)(^|[^a-záéíóúñ]){phrase.replace(' ', '[ _]')}($|[^a-záéíóúñ])", f"$1{idioms[phrase]}$2")
    return c


def tokens(c: Column) -> Column:
    return F.filter(F.split(F.lower(c), "[^a-z0-9áéíóúñüèêàçâôûœäöß\\[\\]:_]+"), lambda t: t != "")


def filter_stop(toks: Column, stop=STOP, protect=PROTECTED) -> Column:
    """Without stop words, but never without negations and words of degree. An empty ``protect`` is the naive baseline."""
    gone = F.array(*(F.lit(w) for w in stop if w not in protect))
    return F.filter(toks, lambda t: ~F.array_contains(gone, t))


def lemmatize(toks: Column, lexicon: dict[str, str] = LEMMAS, protect=PROTECTED) -> Column:
    pairs = [F.lit(x) for k, v in lexicon.items() if k not in protect for x in (k, v)]
    table = F.create_map(*pairs)
    return F.transform(toks, lambda t: F.coalesce(F.try_element_at(table, t), t))


class ReviewPipeline:
    """The steps in their order: repair, NFKC, emoji names, masks, idioms, words, stop words, lemmas. Any of them can be left out by name.

    ``clean`` ends with the words, so that synthetic rows are made of clean ones; ``lemmas`` follows augmentation. A null text has no words.
    """

    TEXT_STEPS = ("repair", "nfkc", "demojize", "mask", "idioms")

    def __init__(self, without: tuple[str, ...] = (), stop=STOP, protect=PROTECTED, idioms: dict[str, str] = IDIOMS, lexicon: dict[str, str] = LEMMAS):
        self.without, self.stop, self.protect, self.idioms, self.lexicon = without, stop, protect, idioms, lexicon

    def leaving(self, steps: tuple[str, ...]) -> ReviewPipeline:
        """The same without these steps too, for texts that have been through them."""
        return ReviewPipeline((*self.without, *steps), self.stop, self.protect, self.idioms, self.lexicon)

    def texts(self, c: Column, steps: tuple[str, ...] = TEXT_STEPS) -> Column:
        """The text after those of the steps that aren't left out."""
        does = {"mask": mask, "idioms": lambda x: normalize_idioms(x, self.idioms)}
        steps = tuple(name for name in steps if name not in self.without)
        c = characters(F.coalesce(c, F.lit("")), tuple(name for name in steps if name in CHARACTER_STEPS))
        for name in steps:
            c = does[name](c) if name in does else c
        return c

    def clean(self, c: Column) -> Column:
        toks = tokens(self.texts(c))
        return toks if "stop" in self.without else filter_stop(toks, self.stop, self.protect)

    def lemmas(self, toks: Column) -> Column:
        return toks if "lemmas" in self.without else lemmatize(toks, self.lexicon, self.protect)

    def fields(self, df: DataFrame, fields: list[str]) -> DataFrame:
        """``df`` with the clean words of each field in its place."""
        return df.withColumns({f: self.clean(F.col(f)) for f in fields})

    def encode(self, df: DataFrame, fields: list[str], encoder=None, to: str = "features") -> DataFrame:
        """The lemmas of each field of words, encoded one after the other."""
        encoder = encoder or HashedProjectionEncoder()
        return df.withColumn(to, F.concat(*(encoder.encode(self.lemmas(F.col(f))) for f in fields)))


class ModelEncoder:
    """Any sentence model: ``load`` is called once a worker and batch stream and returns a function from a list of texts to a list of vectors."""

    def __init__(self, load, batch: int = 64):
        self.load, self.batch = load, batch

    def encode(self, toks: Column) -> Column:
        load, size = self.load, self.batch

        def run(frames: Iterator[pd.Series]) -> Iterator[pd.Series]:
            model = load()
            for s in frames:
                texts = [t or "" for t in s]
                out = [[float(x) for x in v] for at in range(0, len(texts), size) for v in model(texts[at : at + size])]
                yield pd.Series(out, dtype=object)

        return F.pandas_udf(run, "array<double>")(F.array_join(F.coalesce(toks, F.array().cast("array<string>")), " "))


def title_body(c: Column, words: int = 12) -> tuple[Column, Column]:
    """The first line and the rest; where there is one line only, its first words and the rest."""
    lines = F.locate("\n", c)
    parts = F.split(c, " ")
    title = F.when(lines > 0, F.substring(c, F.lit(1), lines - 1)).otherwise(F.array_join(F.slice(parts, 1, words), " "))
    body = F.when(lines > 0, F.substring(c, lines + 1, F.length(c))).otherwise(F.array_join(F.slice(parts, words + 1, F.greatest(F.size(parts), F.lit(1))), " "))
    return title, body


def page_fields(df: DataFrame) -> DataFrame:
    """page_id, title, body and lang of raw pages."""
    html = F.col("html")
    body = F.regexp_replace(F.regexp_replace(html, "(?s)<(script|style|title)[^>]*>.*?</(script|style|title)>", " "), "(?s)<[^>]*>", " ")
    return df.select("page_id", F.regexp_extract(html, "(?s)<title>(.*?)</title>", 1).alias("title"), F.trim(F.regexp_replace(body, SPACE, " ")).alias("body"), F.regexp_extract(html, '<html lang="([a-z]+)"', 1).alias("lang"))


def tfidf(df: DataFrame, toks: str, size: int = 1 << 18, to: str = "tfidf") -> DataFrame:
    """Sparse counts by hash, weighted by rarity; the high-dimensional baseline."""
    from pyspark.ml.feature import IDF, HashingTF

    counted = HashingTF(inputCol=toks, outputCol="_tf", numFeatures=size).transform(df)
    return IDF(inputCol="_tf", outputCol=to).fit(counted).transform(counted).drop("_tf")


class HashedProjectionEncoder:
    """Texts to d numbers: signed hashes of words and word pairs, to unit length. A stand-in for contextual encoders, not their equal."""

    def __init__(self, d: int = 768, pairs: bool = True):
        self.d, self.pairs = d, pairs

    def encode(self, toks: Column) -> Column:
        d, pairs = self.d, self.pairs

        def run(frames: Iterator[pd.Series]) -> Iterator[pd.Series]:
            import numpy as np

            for s in frames:
                out = []
                for hashes in s:
                    v = np.zeros(d)
                    if hashes is not None and len(hashes):
                        h = np.asarray(hashes, np.int64).view(np.uint64)
                        if pairs:
                            both = (h[:-1] * np.uint64(0x9E3779B97F4A7C15)) ^ h[1:]
                            h = np.append(h, (both ^ (both >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9))
                        np.add.at(v, (h % np.uint64(d)).astype(np.int64), 1.0 - 2.0 * (h >> np.uint64(63)).astype(float))
                        v /= max(np.linalg.norm(v), 1e-12)
                    out.append(v.tolist())
                yield pd.Series(out, dtype=object)

        return F.pandas_udf(run, "array<double>")(F.transform(toks, lambda t: F.xxhash64(t)))


class FittedEncoder:
    """A Spark ML model from token lists to vectors, behind the shape that ``encode_fields`` takes. Empty and null lists give zeros."""

    def __init__(self, stages, d: int):
        self.stages, self.d = stages, d

    def transform(self, df: DataFrame, toks: Column, to: str) -> DataFrame:
        from pyspark.ml.functions import vector_to_array

        out = df.withColumn("_t0", F.coalesce(toks, F.array().cast("array<string>")))
        for model in self.stages:
            out = model.transform(out)
        out = out.withColumn(to, vector_to_array(f"_t{len(self.stages)}"))
        return out.drop(*(f"_t{i}" for i in range(len(self.stages) + 1)))


def fit_word2vec(df: DataFrame, toks: Column, d: int = 64, min_count: int = 5, window: int = 5, iterations: int = 1) -> FittedEncoder:
    """Means of word vectors. The vocabulary, with ``min_count`` uses at least, goes through the driver: raise that with the corpus."""
    from pyspark.ml.feature import Word2Vec

    rows = df.select(F.coalesce(toks, F.array().cast("array<string>")).alias("_t0"))
    return FittedEncoder([Word2Vec(inputCol="_t0", outputCol="_t1", vectorSize=d, minCount=min_count, windowSize=window, maxIter=iterations, seed=42).fit(rows)], d)


def fit_tfidf_pca(df: DataFrame, toks: Column, d: int = 32, size: int = 1024) -> FittedEncoder:
    """Hashed, rarity-weighted counts in ``size`` columns, projected to d; the driver sees size by size numbers."""
    from pyspark.ml.feature import IDF, PCA, HashingTF

    rows = df.select(F.coalesce(toks, F.array().cast("array<string>")).alias("_t0"))
    counts = HashingTF(inputCol="_t0", outputCol="_t1", numFeatures=size)
    rows = counts.transform(rows)
    rarity = IDF(inputCol="_t1", outputCol="_t2").fit(rows)
    return FittedEncoder([counts, rarity, PCA(k=d, inputCol="_t2", outputCol="_t3").fit(rarity.transform(rows))], d)


def encode_fields(df: DataFrame, fields: list[str], encoder=None, to: str = "features") -> DataFrame:
    """The encodings of each field, one after the other."""
    encoder = encoder or HashedProjectionEncoder()
    if isinstance(encoder, FittedEncoder):
        for i, f in enumerate(fields):
            df = encoder.transform(df, tokens(F.coalesce(F.col(f), F.lit(""))), f"_field{i}")
        names = [f"_field{i}" for i in range(len(fields))]
        return df.withColumn(to, F.concat(*names)).drop(*names)
    return df.withColumn(to, F.concat(*(encoder.encode(tokens(F.coalesce(F.col(f), F.lit("")))) for f in fields)))


def dup_groups(df: DataFrame) -> DataFrame:
    """Rows with the smallest id and the size of their group of equal texts."""
    groups = df.groupBy(F.md5(F.col("text").cast("binary")).alias("content_hash")).agg(F.min("doc_id").alias("first_id"), F.count(F.lit(1)).alias("copies"))
    return df.select("doc_id", F.md5(F.col("text").cast("binary")).alias("content_hash")).join(groups, "content_hash").select("doc_id", "first_id", "copies")


def decontaminate(train: DataFrame, held: DataFrame, n: int = 8) -> DataFrame:
    """Rows of ``train`` that share no run of n words with ``held``."""
    words = train.select("doc_id", F.filter(F.split(F.lower("text"), "[^a-z0-9]+"), lambda t: t != "").alias("w"))
    grams = words.where(F.size("w") >= n).select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(0), F.size("w") - n), lambda i: F.xxhash64(F.slice(F.col("w"), i + 1, n))))).alias("g"))
    own = held.select(F.filter(F.split(F.lower("text"), "[^a-z0-9]+"), lambda t: t != "").alias("w")).where(F.size("w") >= n)
    bad = own.select(F.explode(F.transform(F.sequence(F.lit(0), F.size("w") - n), lambda i: F.xxhash64(F.slice(F.col("w"), i + 1, n)))).alias("g")).distinct()
    return train.join(grams.join(bad, "g", "left_semi").select("doc_id").distinct(), "doc_id", "left_anti")
