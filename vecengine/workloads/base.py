"""Registration of queries, and the SQL pieces that many of them share."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        if key in QUERIES:
            raise ValueError(f"{key} is there already")
        QUERIES[key] = f
        if sql:
            ORACLE_SQL[key] = sql
        return f

    return add


#: Vectors in double precision; rows and held-out queries.
EMB = "emb AS (SELECT vec_id AS id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS vec, label FROM embeddings)"
DB = f"{EMB}, db AS (SELECT id, vec FROM emb WHERE id % 10 <> 0), q AS (SELECT id AS qid, vec FROM emb WHERE id % 10 = 0)"
MEAN = (
    f"{DB}, mu AS (SELECT j, round(CAST(sum(CAST(x AS DECIMAL(38,15))) AS DOUBLE) / count(*), 12) AS mu FROM "
    "(SELECT unnest(range(0, len(vec))) AS j, unnest(vec) AS x FROM db) GROUP BY j), "
    "mean AS (SELECT list(mu ORDER BY j) AS m FROM mu), "
    "cen AS (SELECT id, list_transform(range(1, len(vec) + 1), lambda i: vec[i] - m[i]) AS vec FROM db, mean)"
)


def fold(parts: str, over: str) -> str:
    """Left-to-right sum of an expression in i over the places of a list."""
    return f"list_reduce(list_transform(range(1, len({over}) + 1), lambda i: {parts}), lambda s, x: s + x)"


def sq_l2(a: str, b: str) -> str:
    return fold(f"({a}[i] - {b}[i]) * ({a}[i] - {b}[i])", a)


def dot(a: str, b: str) -> str:
    return fold(f"{a}[i] * {b}[i]", a)


def score(a: str, b: str, kind: str = "l2") -> str:
    if kind == "l2":
        return f"-sqrt({sq_l2(a, b)})"
    if kind == "ip":
        return dot(a, b)
    return f"{dot(a, b)} / (sqrt({dot(a, a)}) * sqrt({dot(b, b)}))"


def knn(db: str = "db", q: str = "q", k: int = 10, kind: str = "l2", where: str = "TRUE") -> str:
    """A query for (qid, rank, id, score)."""
    return (
        f"SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS rank, id, score FROM "
        f"(SELECT {q}.qid, {db}.id, {score(f'{q}.vec', f'{db}.vec', kind)} AS score FROM {q}, {db} WHERE {where}) "
        f"QUALIFY rank <= {k}"
    )


def code_of(x: str, lo: str, step: str, bits: int) -> str:
    return f"CAST(CASE WHEN {step} > 0 THEN greatest(0, least({2**bits - 1}, floor(({x} - {lo}) / {step} + 0.5))) ELSE 0 END AS INTEGER)"


def pv(bits: int, source: str = "cen", name: str = "enc") -> str:
    """CTEs: per-vector codes of a centered table."""
    return (
        f"{name}_b AS (SELECT id, vec, list_min(vec) AS lo, (list_max(vec) - list_min(vec)) / {float(2**bits - 1)} AS step FROM {source}), "
        f"{name} AS (SELECT id, vec, lo, step, list_transform(vec, lambda x: {code_of('x', 'lo', 'step', bits)}) AS codes FROM {name}_b)"
    )


def gl(bits: int, source: str = "cen", name: str = "enc") -> str:
    """The same with bounds of all vectors together."""
    return (
        f"{name}_g AS (SELECT min(list_min(vec)) AS lo, (max(list_max(vec)) - min(list_min(vec))) / {float(2**bits - 1)} AS step FROM {source}), "
        f"{name} AS (SELECT id, vec, lo, step, list_transform(vec, lambda x: {code_of('x', 'lo', 'step', bits)}) AS codes FROM {source}, {name}_g)"
    )


def residual(bits2: int, source: str = "enc", name: str = "enc2") -> str:
    """CTE: second-level codes."""
    top = 2**bits2 - 1
    left = "(vec[i] - (lo + step * CAST(codes[i] AS DOUBLE)))"
    return (
        f"{name} AS (SELECT *, list_transform(range(1, len(vec) + 1), lambda i: CAST(CASE WHEN step / {float(top)} > 0 THEN greatest(0, least({top}, "
        f"floor(({left} + step / 2) / (step / {float(top)}) + 0.5))) ELSE 0 END AS INTEGER)) AS codes2 FROM {source})"
    )


def decoded(source: str = "enc", name: str = "dec") -> str:
    return f"{name} AS (SELECT id, list_transform(range(1, len(codes) + 1), lambda i: (lo + step * CAST(codes[i] AS DOUBLE)) + m[i]) AS vec FROM {source}, mean)"


def decoded2(bits2: int, source: str = "enc2", name: str = "dec") -> str:
    top = float(2**bits2 - 1)
    return (
        f"{name} AS (SELECT id, list_transform(range(1, len(codes) + 1), lambda i: ((lo + step * CAST(codes[i] AS DOUBLE)) + "
        f"(CAST(codes2[i] AS DOUBLE) * (step / {top}) - step / 2)) + m[i]) AS vec FROM {source}, mean)"
    )


def codec_sql(codec: str, name: str = "dec") -> str:
    """CTEs from cen to the decoded table ``name``."""
    kind, bits = codec[:2], [int(b) for b in codec[2:].split("x")]
    tag = f"{name}_e"
    if kind == "pd":
        b = bits[0]
        return (
            f"{tag}b AS (SELECT j, min(x) AS lo, (max(x) - min(x)) / {float(2**b - 1)} AS step FROM (SELECT unnest(range(0, len(vec))) AS j, unnest(vec) AS x FROM cen) GROUP BY j), "
            f"{tag}l AS (SELECT list(lo ORDER BY j) AS los, list(step ORDER BY j) AS steps FROM {tag}b), "
            f"{name} AS (SELECT id, list_transform(range(1, len(vec) + 1), lambda i: (los[i] + steps[i] * CAST({code_of('vec[i]', 'los[i]', 'steps[i]', b)} AS DOUBLE)) + m[i]) AS vec FROM cen, mean, {tag}l)"
        )
    first = (pv if kind == "pv" else gl)(bits[0], "cen", tag)
    if len(bits) == 1:
        return f"{first}, {decoded(tag, name)}"
    return f"{first}, {residual(bits[1], tag, tag + '2')}, {decoded2(bits[1], tag + '2', name)}"


def text_of(codes: str) -> str:
    return f"array_to_string(list_transform({codes}, lambda c: CAST(c AS VARCHAR)), ',')"


def recall_sql(found: str, truth: str) -> str:
    """Average share of the true ids among the found ones."""
    return f"SELECT (SELECT count(*) FROM {found} f JOIN {truth} t ON f.qid = t.qid AND f.id = t.id) / CAST((SELECT count(*) FROM {truth}) AS DOUBLE)"
