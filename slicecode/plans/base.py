"""The registry's decorator and the SQL fragments that many oracles share (DuckDB dialect)."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    """Register a function (spark, sf_dir) -> DataFrame under its name, with its SQL if there is one."""

    def put(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return put


def label(x: str) -> str:
    return f"strftime(CAST(DATE '2017-01-01' + to_months(CAST({x} AS INTEGER)) AS DATE), '%Y-%m')"


DOCS = r"""docs AS (SELECT CASE WHEN CAST(regexp_extract(source, '(\d+)$', 1) AS INTEGER) < 10 THEN 'reference_articles' ELSE 'news_articles' END AS source,
  doc_id AS item_id, CAST(doc_id % 83 AS INTEGER) AS m, text AS body FROM documents)"""
CODE = """code AS (SELECT 'code_files' AS source, page_id AS item_id, CAST(page_id % 83 AS INTEGER) AS m, html AS body FROM pages)"""
BODY = r"""trim(regexp_replace(replace(replace(replace(replace(regexp_replace(regexp_extract(html, '(?s)<article>(.*)</article>', 1), '<[^>]*>', ' ', 'g'), '&quot;', '"'), '&lt;', '<'), '&gt;', '>'), '&amp;', '&'), '[ \t\n]+', ' ', 'g'))"""
PAPERS = f"papers AS (SELECT 'paper_bodies' AS source, page_id AS item_id, CAST(page_id % 83 AS INTEGER) AS m, {BODY} AS body FROM pages)"
ORDERS = """lines AS (SELECT 'order_log' AS source, o_orderkey AS item_id, CAST((year(o_orderdate) + 22 - 2017) * 12 + month(o_orderdate) - 1 AS INTEGER) AS m,
  concat_ws('|', CAST(o_orderkey AS VARCHAR), CAST(o_custkey AS VARCHAR), o_orderstatus, o_orderpriority) AS body FROM orders)"""
SIZES = f"""{DOCS}, {CODE}, {PAPERS}, {ORDERS},
sizes AS (SELECT source, item_id, m, CAST(strlen(body) AS BIGINT) AS raw_bytes FROM docs UNION ALL SELECT source, item_id, m, strlen(body) FROM code UNION ALL SELECT source, item_id, m, strlen(body) FROM papers
  UNION ALL SELECT source, item_id, m, strlen(body) FROM lines UNION ALL SELECT 'dialogues', conv_id, CAST(conv_id % 83 AS INTEGER), strlen(text) FROM conversations
  UNION ALL SELECT 'gray_patches', vec_id, CAST(vec_id % 83 AS INTEGER), len(embedding) FROM embeddings
  UNION ALL SELECT 'sample_series', l_orderkey, CAST((year(l_shipdate) + 22 - 2017) * 12 + month(l_shipdate) - 1 AS INTEGER), 2 FROM lineitem)"""


def tokens(source: str, name: str = "tok", seq: str = "regexp_extract_all(hex(encode(body)), '..')") -> str:
    """CTE of long tokens (source, m, item_id, pos, sym) of a relation with those columns and body."""
    return f"{name} AS (SELECT source, m, item_id, unnest(h) AS sym, generate_subscripts(h, 1) - 1 AS pos FROM (SELECT source, m, item_id, {seq} AS h FROM {source}))"


def grams(chunk: int | None = 2048, order: int = 2) -> str:
    """CTE of grams (source, m, ctx, sym, n) from tok."""
    at = f"pos % {chunk}" if chunk else "pos"
    cases = "".join(f" WHEN {at} = {k} THEN {' || '.join(f'p{j}' for j in range(k, 0, -1)) or repr('')}" for k in range(order))
    ctx = f"CASE{cases} ELSE {' || '.join(f'p{j}' for j in range(order, 0, -1))} END" if order else "''"
    lags = "".join(f", lag(sym, {j}) OVER w AS p{j}" for j in range(1, order + 1))
    return f"grams AS (SELECT source, m, ctx, sym, CAST(count(*) AS BIGINT) AS n FROM (SELECT source, m, sym, {ctx} AS ctx FROM (SELECT *{lags} FROM tok WINDOW w AS (PARTITION BY source, item_id ORDER BY pos))) GROUP BY ALL)"


def backoff(x: str, order: int, where: str, smoothing: str = "wb") -> str:
    """CTEs that end in s_{x} (ctx, sym, p): the law of the grams under ``where`` for all distinct grams."""
    out = []
    for d in range(order + 1):
        h = "''" if d == 0 else f"right(ctx, {2 * d})"
        out.append(f"c{d}_{x} AS (SELECT {h} AS h, sym, sum(n) AS c FROM grams WHERE length(ctx) >= {2 * d} AND {where} GROUP BY ALL)")
        out.append(f"t{d}_{x} AS (SELECT h, sum(c) AS n, count(*) AS t FROM c{d}_{x} GROUP BY h)")
    inner = "SELECT g.ctx, g.sym" + "".join(f", c{d}.c AS c{d}, t{d}.n AS n{d}, t{d}.t AS t{d}" for d in range(order + 1)) + " FROM (SELECT DISTINCT ctx, sym FROM grams) g"
    for d in range(order + 1):
        h = "''" if d == 0 else f"right(g.ctx, {2 * d})"
        inner += f" LEFT JOIN t{d}_{x} t{d} ON t{d}.h = {h} AND length(g.ctx) >= {2 * d} LEFT JOIN c{d}_{x} c{d} ON c{d}.h = {h} AND c{d}.sym = g.sym AND length(g.ctx) >= {2 * d}"
    body, last = inner, "CAST(1.0 AS DOUBLE) / 256"
    for d in range(order + 1):
        new = f"(CAST(coalesce(c{d}, 0) AS DOUBLE) + t{d} * q) / (n{d} + t{d})" if smoothing == "wb" else f"(greatest(CAST(coalesce(c{d}, 0) AS DOUBLE) - CAST(0.75 AS DOUBLE), CAST(0 AS DOUBLE)) + CAST(0.75 AS DOUBLE) * t{d} * q) / n{d}"
        prior = last if d == 0 else "p"
        body = f"SELECT * EXCLUDE (q), CASE WHEN n{d} IS NULL THEN q ELSE {new} END AS p FROM (SELECT * {'EXCLUDE (p)' if d else ''}, {prior} AS q FROM ({body}))"
    out.append(f"s_{x} AS (SELECT ctx, sym, p FROM ({body}))")
    return ", ".join(out)


MICRO = "CAST(round(-log2(p) * 1000000) AS BIGINT)"
TEXTS = "'reference_articles', 'news_articles'"
#: Models of the rate oracles: name -> (order, last training month, trained on code too, size class).
RATE_MODELS = {"early_o1": (1, 47, False, "small"), "early_o2": (2, 47, False, "large"), "late_o1": (1, 68, False, "small"), "late_o2": (2, 68, False, "large"), "late_o2_code": (2, 68, True, "large")}


def rate_ctes() -> str:
    """WITH list that ends in series (source, model_id, m, micro, raw_bytes, rate) of the rate models and the uniform law."""
    laws = ", ".join(backoff(x, k, f"m <= {until} AND source IN ({TEXTS}{', ' + repr('code_files') if code else ''})") for x, (k, until, code, _) in RATE_MODELS.items())
    each = " UNION ALL ".join(f"SELECT source, '{x}' AS model_id, m, CAST(sum(n * {MICRO}) AS BIGINT) AS micro, CAST(sum(n) AS BIGINT) AS raw_bytes FROM grams JOIN s_{x} USING (ctx, sym) GROUP BY source, m" for x in RATE_MODELS)
    return f"""{DOCS}, {CODE}, slices AS (SELECT * FROM docs UNION ALL SELECT * FROM code), {tokens('slices')}, {grams(2048, 2)}, {laws},
totals AS ({each} UNION ALL SELECT source, 'uniform', m, CAST(sum(n) * 8000000 AS BIGINT), CAST(sum(n) AS BIGINT) FROM grams GROUP BY source, m),
series AS (SELECT *, round(100.0 * micro / 1000000 / (8.0 * raw_bytes), 4) AS rate FROM totals)"""


RATES = rate_ctes()
def mean_sql(where: str) -> str:
    return f"round(CAST(sum(CAST(round(rate * 10000) AS BIGINT)) FILTER (WHERE {where}) AS DOUBLE) / count(*) FILTER (WHERE {where}) / 10000, 8)"


PERIODS = f"""{RATES}, rates0 AS (SELECT source, model_id, {mean_sql('true')} AS r_all, {mean_sql('m < 72')} AS r_train, {mean_sql('m >= 72')} AS r_test FROM series GROUP BY source, model_id)"""
ROBUST = f"""{PERIODS}, rates1 AS (SELECT *, round(r_test - r_train, 8) AS gap FROM rates0),
rates AS (SELECT *, round(gap / r_train, 6) AS gap_rel, CASE WHEN gap > 0 THEN 'up' WHEN gap < 0 THEN 'down' ELSE 'flat' END AS arrow FROM rates1)"""
CLASSES = "classes AS (SELECT * FROM (VALUES " + ", ".join(f"('{x}', '{c}')" for x, (_, _, _, c) in RATE_MODELS.items()) + ") v(model_id, size_class))"
