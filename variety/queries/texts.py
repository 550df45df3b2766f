"""Text preparation and augmentation."""

from pyspark.sql import functions as F

from ..functions.hashing import uniform, uniform_sql
from ..operators import augment as A
from ..operators import text as X
from ..plans import workloads as W
from ..sources.tables import load
from .registry import query

TOKENS = "list_filter(string_split_regex(lower(text), '[^a-z0-9áéíóúñüèêàçâôûœäöß\\[\\]:_]+'), lambda t: t <> '')"


def _docs(spark, d, lang=None):
    rows = load(spark, d, "documents")
    return rows.where(F.col("lang") == lang) if lang else rows


@query(
    "txt_mask_entities",
    """SELECT page_id, md5(regexp_replace(regexp_replace(regexp_replace(html, '<[A-Za-z/!][^>]*>', '[HTML]', 'g'), '(https?://|www[.])[^ "<>]+', '[URL]', 'g'), '[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+[.][A-Za-z]+', '[EMAIL]', 'g')) AS masked FROM pages""",
)
def _(spark, d):
    return load(spark, d, "pages").select("page_id", F.md5(X.mask(F.col("html")).cast("binary")).alias("masked"))


@query("txt_page_fields", """SELECT page_id, regexp_extract(html, '(?s)<title>(.*?)</title>', 1) AS title, regexp_extract(html, '<html lang="([a-z]+)"', 1) AS lang FROM pages""")
def _(spark, d):
    return X.page_fields(load(spark, d, "pages")).select("page_id", "title", "lang")


@query("txt_idioms", "SELECT * FROM (VALUES (1, 'esta bien'), (2, 'es bueno'), (3, 'muy dificil'), (4, 'padres')) t(id, text)")
def _(spark, d):
    rows = spark.createDataFrame([(1, "esta bien"), (2, "esta chido"), (3, "muy canon"), (4, "padres")], "id int, text string")
    return rows.select("id", X.normalize_idioms(F.col("text")).alias("text"))


@query("txt_tokens", f"SELECT doc_id, len({TOKENS}) AS n_tokens, md5(array_to_string({TOKENS}, ' ')) AS tokens FROM documents WHERE lang = 'es'")
def _(spark, d):
    rows = _docs(spark, d, "es").select("doc_id", X.tokens(F.col("text")).alias("t"))
    return rows.select("doc_id", F.size("t").cast("long").alias("n_tokens"), F.md5(F.array_join("t", " ").cast("binary")).alias("tokens"))


def _stop(words):
    return "[" + ", ".join(f"'{w}'" for w in words) + "]"


for _name, _protect in (("protected", X.PROTECTED), ("naive", ())):
    _gone = _stop([w for w in X.STOP if w not in _protect])

    @query(f"txt_stop_{_name}", f"SELECT doc_id, len(list_filter({TOKENS}, lambda t: NOT list_contains({_gone}, t))) AS n_tokens FROM documents WHERE lang = 'es'")
    def _(spark, d, protect=_protect):
        rows = _docs(spark, d, "es").select("doc_id", X.tokens(F.col("text")).alias("t"))
        return rows.select("doc_id", F.size(X.filter_stop(F.col("t"), protect=protect)).cast("long").alias("n_tokens"))


@query("txt_negation_kept", f"SELECT count(*) AS documents, CAST(sum(len(list_filter({TOKENS}, lambda t: t = 'no' OR t = 'nunca' OR t = 'jamás'))) AS BIGINT) AS before, CAST(sum(len(list_filter({TOKENS}, lambda t: t = 'no' OR t = 'nunca' OR t = 'jamás'))) AS BIGINT) AS after FROM documents WHERE lang = 'es'")
def _(spark, d):
    count = lambda c: F.size(F.filter(c, lambda t: t.isin("no", "nunca", "jamás")))
    rows = _docs(spark, d, "es").select(X.tokens(F.col("text")).alias("t"))
    return rows.agg(F.count(F.lit(1)).alias("documents"), F.sum(count(F.col("t"))).alias("before"), F.sum(count(X.filter_stop(F.col("t")))).alias("after"))


@query("txt_lemma_dict", "SELECT * FROM (VALUES (1, 'comer comer comer'), (2, 'nunca ser bueno')) t(id, lemmas)")
def _(spark, d):
    rows = spark.createDataFrame([(1, "comimos comiendo comeremos"), (2, "nunca fue buena")], "id int, text string")
    return rows.select("id", F.array_join(X.lemmatize(X.tokens(F.col("text"))), " ").alias("lemmas"))


LITERALS = [(1, "estÃ¡ bien", "está bien"), (2, "está bien", "está bien"), (3, "ﬁno ①", "fino 1"), (4, "ok 👍", "ok :thumbs_up:"), (5, "❤️", ":red_heart:")]


@query("txt_repair", "SELECT * FROM (VALUES (1, 'está bien'), (2, 'está bien'), (3, 'fino 1'), (4, 'ok :thumbs_up:'), (5, ':red_heart:')) t(id, clean)")
def _(spark, d):
    rows = spark.createDataFrame([r[:2] for r in LITERALS], "id int, text string")
    return rows.select("id", X.demojize(X.nfkc(X.repair(F.col("text")))).alias("clean"))


@query("txt_sanitize_documents", "SELECT doc_id, md5(text) AS clean FROM documents WHERE lang = 'en'")
def _(spark, d):
    return _docs(spark, d, "en").select("doc_id", F.md5(X.demojize(X.nfkc(X.repair(F.col("text")))).cast("binary")).alias("clean"))


@query(
    "txt_tfidf_top",
    f"""WITH t AS (SELECT doc_id, lang, unnest({TOKENS}) AS w FROM documents), n AS (SELECT count(*) AS n FROM documents), df AS (SELECT w, count(DISTINCT doc_id) AS df FROM t GROUP BY w), tf AS (SELECT lang, w, count(*) AS tf FROM t GROUP BY 1, 2),
    s AS (SELECT lang, tf.w, round(tf * ln((n + 1) / (df + 1)), 4) AS score FROM tf JOIN df ON df.w = tf.w CROSS JOIN n), r AS (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY score DESC, w) AS k FROM s) SELECT lang, w AS term, score FROM r WHERE k <= 10""",
)
def _(spark, d):
    from pyspark.sql import Window

    t = _docs(spark, d).select("doc_id", "lang", F.explode(X.tokens(F.col("text"))).alias("w"))
    df = t.groupBy("w").agg(F.count_distinct("doc_id").alias("df"))
    n = F.broadcast(_docs(spark, d).agg(F.count(F.lit(1)).alias("n")))
    s = t.groupBy("lang", "w").agg(F.count(F.lit(1)).alias("tf")).join(df, "w").join(n).select("lang", F.col("w").alias("term"), F.round(F.col("tf") * F.log((F.col("n") + 1) / (F.col("df") + 1)), 4).alias("score"))
    rank = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("score"), "term"))
    return s.withColumn("k", rank).where("k <= 10").drop("k")


@query("txt_title_body", "SELECT doc_id, length(CASE WHEN position(chr(10) IN text) > 0 THEN split_part(text, chr(10), 1) ELSE array_to_string(list_slice(string_split(text, ' '), 1, 12), ' ') END) AS title_chars FROM documents")
def _(spark, d):
    title, _ = X.title_body(F.col("text"))
    return _docs(spark, d).select("doc_id", F.length(title).cast("long").alias("title_chars"))


@query("txt_encode_shape")
def _(spark, d):
    rows = W.reviews(spark, d)
    one, two = X.encode_fields(rows, ["text"], to="joined"), X.encode_fields(rows, ["title", "body"])
    return one.agg(F.max(F.size("joined")).alias("joined")).join(F.broadcast(two.agg(F.max(F.size("features")).alias("two_fields"))))


def _encoder_gap(spark, d, fit_encoder):
    from ..models.registry import fit
    from ..operators import metrics as M
    from ..operators.sampling import holdout

    rows = holdout(W.reviews(spark, d), "doc_id").withColumn("label", (F.col("type") == "en").cast("double"))
    encoder = fit_encoder(rows.where("split = 'train'"), X.tokens(F.coalesce(F.col("body"), F.lit(""))))
    coded = X.encode_fields(rows, ["title", "body"], encoder).select("doc_id", "split", "label", "features")
    model = fit("logistic", coded.where("split = 'train'"), None, "binary")
    return M.gap(model.transform(coded).withColumn("prediction", F.col("prediction").cast("double")))


@query("txt_encode_word2vec")
def _(spark, d):
    return _encoder_gap(spark, d, X.fit_word2vec)


@query("txt_encode_tfidf_pca")
def _(spark, d):
    return _encoder_gap(spark, d, X.fit_tfidf_pca)


@query("txt_tfidf")
def _(spark, d):
    rows = X.tfidf(_docs(spark, d).select("doc_id", X.tokens(F.col("text")).alias("t")), "t")
    return rows.select("doc_id", F.size("t").alias("n_tokens"))


@query("txt_dup_groups", "SELECT doc_id, min(doc_id) OVER (PARTITION BY md5(text)) AS first_id, count(*) OVER (PARTITION BY md5(text)) AS copies FROM documents")
def _(spark, d):
    return X.dup_groups(_docs(spark, d))


W8 = "list_filter(string_split_regex(lower(text), '[^a-z0-9]+'), lambda t: t <> '')"


@query(
    "txt_decontaminate",
    f"""WITH w AS (SELECT doc_id, {W8} AS w FROM documents), g AS (SELECT doc_id, array_to_string(list_slice(w, i, i + 7), ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM w WHERE len(w) >= 8)),
    b AS (SELECT {W8} AS w FROM benchmark), h AS (SELECT DISTINCT array_to_string(list_slice(w, i, i + 7), ' ') AS g FROM (SELECT w, unnest(range(1, len(w) - 6)) AS i FROM b WHERE len(w) >= 8))
    SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT g.doc_id FROM g JOIN h ON h.g = g.g)""",
)
def _(spark, d):
    return X.decontaminate(_docs(spark, d), load(spark, d, "benchmark")).select("doc_id")


STARS = f"""r AS (SELECT d.doc_id, CASE WHEN quality = 0 AND toxic = 1 THEN 1 WHEN quality = 0 THEN 2 WHEN toxic = 1 THEN 3 WHEN n_chars < 800 THEN 4 ELSE 5 END AS stars,
    CASE WHEN {uniform_sql("split", "md5(text)")} < 0.2 THEN 'test' ELSE 'train' END AS split FROM documents d JOIN labels l ON l.doc_id = d.doc_id)"""


@query("aug_minority", f"WITH {STARS}, c AS (SELECT stars, count(*) AS n FROM r GROUP BY 1) SELECT CAST(stars AS INTEGER) AS stars, n, max(n) OVER () AS n_max, n < max(n) OVER () * 0.5 AS minority FROM c")
def _(spark, d):
    return A.minority(W.reviews(spark, d), "stars")


@query("aug_truncate", f"SELECT doc_id, CASE WHEN len({TOKENS}) >= 30 THEN greatest(CAST(ceil(len({TOKENS}) * (1 - {uniform_sql('aug', 'doc_id')} * 0.3)) AS BIGINT), 1) ELSE len({TOKENS}) END AS n_tokens FROM documents")
def _(spark, d):
    return _docs(spark, d).select("doc_id", F.size(A.truncate(X.tokens(F.col("text")), uniform("aug", "doc_id"))).cast("long").alias("n_tokens"))


@query("aug_suffix", f"SELECT doc_id, n_chars + 1 + length(list_extract(['en general', 'como se esperaba', 'segun lo previsto'], CAST(floor({uniform_sql('aug', 'doc_id')} * 3) AS BIGINT) + 1)) AS chars FROM documents WHERE n_chars < 400")
def _(spark, d):
    rows = _docs(spark, d).where("n_chars < 400")
    return rows.select("doc_id", F.length(A.suffix(F.col("text"), uniform("aug", "doc_id"))).cast("long").alias("chars"))


@query(
    "aug_superset_balance",
    f"""WITH {STARS}, c AS (SELECT stars, count(*) AS n, max(count(*)) OVER () AS m FROM r WHERE split = 'train' GROUP BY 1), k AS (SELECT stars, least(5, greatest(CAST(ceil(0.5 * m / n) AS INTEGER) - 1, 0)) AS k FROM c)
    SELECT CAST(r.stars AS INTEGER) AS stars, split, count(*) + CAST(CASE WHEN split = 'train' THEN count(*) * max(k) ELSE 0 END AS BIGINT) AS n FROM r JOIN k ON k.stars = r.stars GROUP BY 1, 2""",
)
def _(spark, d):
    make = lambda g: g.withColumn("text", A.suffix(F.col("text"), uniform("aug", "doc_id", F.col("copy"))))
    return A.superset(W.reviews(spark, d), "doc_id", "stars", make).groupBy("stars", "split").agg(F.count(F.lit(1)).alias("n"))


@query("aug_undersample", f"WITH {STARS}, c AS (SELECT stars, count(*) AS n, min(count(*)) OVER () AS m FROM r GROUP BY 1) SELECT doc_id FROM r JOIN c ON c.stars = r.stars WHERE {uniform_sql('under', 'doc_id')} < m / n")
def _(spark, d):
    return A.undersample(W.reviews(spark, d).select("doc_id", "stars"), "doc_id", "stars").select("doc_id")


@query("aug_oversample", f"WITH {STARS}, c AS (SELECT stars, count(*) AS n, max(count(*)) OVER () AS m FROM r GROUP BY 1) SELECT CAST(stars AS INTEGER) AS stars, n * (1 + least(5, greatest(CAST(ceil(m / n) AS INTEGER) - 1, 0))) AS n FROM c")
def _(spark, d):
    return A.oversample(W.reviews(spark, d).select("doc_id", "stars"), "doc_id", "stars").groupBy("stars").agg(F.count(F.lit(1)).alias("n"))


@query("aug_back_translate")
def _(spark, d):
    rows = _docs(spark, d, "es").select("doc_id", X.tokens(F.col("text")).alias("t"))
    return rows.select("doc_id", F.size(F.array_except(A.back_translate(F.col("t"), F.col("doc_id")), F.col("t"))).alias("new_words"))


@query("aug_pivot_paraphrase")
def _(spark, d):
    rows = _docs(spark, d, "es").select("doc_id", X.tokens(F.col("text")).alias("t"))
    return rows.select("doc_id", F.size(F.array_except(A.pivot_paraphrase(F.col("t"), F.col("doc_id"), 2), F.col("t"))).alias("new_words"))
