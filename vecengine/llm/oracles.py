"""SQL for the operators that SQL can express: the same results by brute force."""

from __future__ import annotations

#: Smallest id that each vertex of ``links(a, b)`` (both directions) reaches.
_REACHED = (
    "walk AS (SELECT a AS id, a AS far FROM links UNION SELECT walk.id, links.b FROM walk JOIN links ON links.a = walk.far), "
    "reached AS (SELECT id, min(far) AS component FROM walk GROUP BY id)"
)
_SPACES = r"[\x20\x09-\x0D]+"


def ngram_join(n: int, num: int, den: int) -> str:
    shingle = " || ' ' || ".join(f"w[i + {k}]" for k in range(n))
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return (
        f"WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), '{upper}', '{upper.lower()}'), '{_SPACES}'), lambda x: x <> '') AS w FROM documents), "
        f"sets AS (SELECT doc_id, list_distinct(CASE WHEN len(w) >= {n} THEN list_transform(range(1, len(w) - {n - 2}), lambda i: {shingle}) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS s FROM w), "
        "t AS (SELECT doc_id, len(s) AS n, unnest(s) AS x FROM sets), "
        f"p AS (SELECT a.doc_id AS a, b.doc_id AS b FROM t a JOIN t b ON a.x = b.x AND a.doc_id <> b.doc_id GROUP BY ALL HAVING {den} * count(*) >= {num} * (any_value(a.n) + any_value(b.n) - count(*))), "
        f"links AS MATERIALIZED (SELECT * FROM p), {_REACHED} "
        "SELECT doc_id, CAST(len(s) AS BIGINT) AS n_shingles, coalesce(component, doc_id) AS component_id FROM sets LEFT JOIN reached ON reached.id = doc_id"
    )


_CRC = (
    "xor(list_reduce(list_concat([4294967295], flatten(list_transform(string_split(CAST(doc_id AS VARCHAR), ''), lambda c: [CAST(ascii(c) AS BIGINT), -1, -1, -1, -1, -1, -1, -1, -1]))), "
    "lambda c, x: CASE WHEN x >= 0 THEN xor(c, x) ELSE xor(c >> 1, (c & 1) * 3988292384) END), 4294967295)"
)


def language_id(size: int) -> str:
    """Profiles of the rows whose crc32(doc_id) mod 4 is not 2, and the out-of-place distances of all rows."""
    grams = " UNION ALL ".join(f"SELECT doc_id, lang, held_out, {k} AS k, unnest(list_transform(range(1, CAST(length(t) AS BIGINT) - {k - 2}), lambda i: substr(t, i, {k}))) AS g FROM d" for k in (1, 2, 3))
    return (
        f"WITH c AS (SELECT doc_id, lang, coalesce({_CRC} % 4 = 2, FALSE) AS held_out, trim(regexp_replace(lower(coalesce(text, '')), '[^\\p{{L}}]+', ' ', 'g')) AS t FROM documents), "
        "d AS (SELECT doc_id, lang, held_out, ' ' || t || ' ' AS t FROM c WHERE t <> ''), "
        f"g AS MATERIALIZED (SELECT doc_id, lang, held_out, k, g, count(*) AS n FROM ({grams}) WHERE g <> ' ' GROUP BY ALL), "
        f"p AS MATERIALIZED (SELECT lang, g, row_number() OVER (PARTITION BY lang ORDER BY sum(n) DESC, any_value(k), g) AS r FROM g WHERE NOT held_out AND lang IS NOT NULL GROUP BY lang, g QUALIFY r <= {size}), "
        f"m AS (SELECT doc_id, g, row_number() OVER (PARTITION BY doc_id ORDER BY n DESC, k, g) AS r FROM g QUALIFY r <= {size}), "
        "l AS (SELECT DISTINCT lang FROM p), "
        f"f AS (SELECT m.doc_id, l.lang, sum(coalesce(abs(p.r - m.r), {size})) AS far FROM m CROSS JOIN l LEFT JOIN p ON p.lang = l.lang AND p.g = m.g GROUP BY ALL), "
        "o AS (SELECT doc_id, list(lang ORDER BY far, lang) AS langs, list(far ORDER BY far, lang) AS fars FROM f GROUP BY doc_id) "
        "SELECT c.doc_id, held_out, coalesce(langs[1], 'und') AS lang_pred, CASE WHEN langs IS NULL THEN 0.0::DOUBLE WHEN len(langs) = 1 THEN 1.0::DOUBLE WHEN fars[1] + fars[2] > 0 THEN 1 - CAST(fars[1] AS DOUBLE) / CAST(fars[1] + fars[2] AS DOUBLE) ELSE 0.5::DOUBLE END AS score "
        "FROM c LEFT JOIN o ON o.doc_id = c.doc_id"
    )


_SOUND = "embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0"


def near_vectors(threshold: float) -> str:
    return (
        f"WITH RECURSIVE v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings WHERE {_SOUND} AND len(list_filter(embedding, lambda x: x <> 0)) > 0), "
        f"links AS MATERIALIZED (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id AND len(a.v) = len(b.v) AND list_cosine_similarity(a.v, b.v) >= {threshold}), "
        f"{_REACHED}, n AS (SELECT a, count(*) AS n FROM links GROUP BY a) "
        "SELECT vec_id, coalesce(n, 0) AS n_links, coalesce(component, vec_id) AS component_id, coalesce(component, vec_id) = vec_id AS kept FROM embeddings LEFT JOIN n ON n.a = vec_id LEFT JOIN reached ON reached.id = vec_id"
    )


def topk(k: int, scale: int) -> str:
    return (
        f"WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor({scale} * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings WHERE {_SOUND}), "
        "s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(range(1, len(c.v) + 1), lambda i: q.v[i] * c.v[i])) AS BIGINT) AS score FROM v q JOIN v c ON q.vec_id % 100 = 0 AND q.vec_id <> c.vec_id AND len(q.v) = len(c.v)) "
        f"SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s QUALIFY rank <= {k}"
    )
