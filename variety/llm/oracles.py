"""SQL for the queries whose whole result SQL can state; it goes over whole tables, all pairs included."""

#: Of equal payloads of 100 bytes or more the smallest page_id answers, the others refer to it.
WARC = """
WITH facts AS (
    SELECT page_id, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages
), firsts AS (
    SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS head FROM facts
)
SELECT page_id, payload_bytes, payload_digest,
    CASE WHEN payload_bytes >= 100 AND page_id <> head THEN 'revisit' ELSE 'response' END AS record_type,
    CASE WHEN payload_bytes >= 100 AND page_id <> head THEN head END AS refers_to
FROM firsts
"""

#: The smallest id that links lead to; ``links`` has each link in both directions, and ids spread along them.
_REACH = """
reach(node, low) AS (
    SELECT u, least(u, v) FROM links
    UNION
    SELECT links.v, reach.low FROM reach JOIN links ON links.u = reach.node
), components AS (
    SELECT node, min(low) AS low FROM reach GROUP BY node
)
"""

#: All pairs of vectors, in double precision.
EMBEDDINGS = f"""
WITH RECURSIVE vectors AS (
    SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS x FROM embeddings
), usable AS MATERIALIZED (
    SELECT vec_id, x FROM vectors
    WHERE x IS NOT NULL AND len(list_filter(x, lambda c: c IS NULL OR NOT isfinite(c))) = 0 AND len(list_filter(x, lambda c: c <> 0)) > 0
), links AS MATERIALIZED (
    SELECT a.vec_id AS u, b.vec_id AS v FROM usable a JOIN usable b ON a.vec_id <> b.vec_id AND list_cosine_similarity(a.x, b.x) >= 0.9
), degrees AS (
    SELECT u, count(*) AS n FROM links GROUP BY u
), {_REACH}
SELECT vec_id, coalesce(degrees.n, 0) AS n_links, coalesce(components.low, vec_id) AS component_id, coalesce(components.low, vec_id) = vec_id AS kept
FROM vectors LEFT JOIN degrees ON degrees.u = vec_id LEFT JOIN components ON components.node = vec_id
"""

#: Texts that share a shingle are compared whole; equal texts stand for each other through their smallest doc_id.
DOCUMENTS = f"""
WITH RECURSIVE split AS (
    SELECT doc_id, md5(coalesce(text, '')) AS same, text,
        list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') AS w
    FROM documents
), heads AS (
    SELECT same, min(doc_id) AS head, any_value(w) AS w FROM split GROUP BY same
), shingles AS MATERIALIZED (
    SELECT head, unnest(list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
        ELSE list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) END)) AS s FROM heads
), sizes AS MATERIALIZED (
    SELECT head, count(*) AS n FROM shingles GROUP BY head
), shared AS MATERIALIZED (
    SELECT a.head AS u, b.head AS v, count(*) AS both FROM shingles a JOIN shingles b ON a.s = b.s AND a.head <> b.head GROUP BY 1, 2
), links AS MATERIALIZED (
    SELECT shared.u, shared.v FROM shared JOIN sizes a ON a.head = shared.u JOIN sizes b ON b.head = shared.v
    WHERE 100 * shared.both >= 85 * (a.n + b.n - shared.both)
), {_REACH}, found AS (
    SELECT split.doc_id, coalesce(sizes.n, 0) AS n_shingles,
        CASE WHEN sizes.n IS NULL THEN split.doc_id ELSE coalesce(components.low, heads.head) END AS component_id
    FROM split JOIN heads USING (same) LEFT JOIN sizes ON sizes.head = heads.head LEFT JOIN components ON components.node = heads.head
)
SELECT doc_id, n_shingles, component_id, doc_id = component_id AS kept FROM found
"""

ORACLE_SQL = {
    "op5_warc_round_trip": WARC,
    "op8_embedding_near_dedup": EMBEDDINGS,
    "op10_near_duplicates": DOCUMENTS,
}
