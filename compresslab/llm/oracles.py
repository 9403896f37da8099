"""DuckDB SQL for the operators that SQL can state: URL judgments, neighbours and the pages of WARC archives."""

from __future__ import annotations

from .url_graph import LINK, RULES


def url_sql(rules=RULES, damping: float = 0.85, rounds: int = 48, threshold: float = 0.5) -> str:
    low = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    rule, verdict = "NULL", "NULL"
    for r, v in sorted(rules, key=lambda x: (len(x[0]), x[0])):
        name, slash, rest = r.partition("/")
        fits = f"(host = '{name}' OR ends_with(host, '.{name}')) AND starts_with(path, '{slash + rest}')"
        rule, verdict = f"CASE WHEN {fits} THEN '{r}' ELSE {rule} END", f"CASE WHEN {fits} THEN '{v}' ELSE {verdict} END"
    link = LINK.removeprefix("(?i)").replace("'", "''")
    steps = "s0 AS (SELECT host, kind, seed AS score FROM seeds)"
    for i in range(rounds):
        steps += f""", m{i} AS MATERIALIZED (SELECT m.b AS host, m.kind, m.share * s.score * {damping}::DOUBLE AS score FROM moves m JOIN s{i} s ON s.host = m.a AND s.kind = m.kind),
s{i + 1} AS MATERIALIZED (SELECT host, kind, sum(score) AS score FROM (SELECT * FROM m{i} UNION ALL SELECT host, kind, seed * (1 - coalesce((SELECT sum(score) FROM m{i} WHERE m{i}.kind = seeds.kind), 0)) FROM seeds) GROUP BY ALL)"""
    return f"""WITH after AS (SELECT page_id, html, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
cut AS (SELECT page_id, html, {low.format("coalesce(regexp_extract(rest, '^[^/?#]*'), '')")} AS host, coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1), '') AS path FROM after),
ruled AS (SELECT page_id, host, path, {rule} AS rule, {verdict} AS verdict FROM cut),
marks AS (SELECT host, CASE WHEN verdict = 'allow' THEN 'trust' ELSE 'distrust' END AS kind, count(*) AS n FROM ruled WHERE host <> '' AND verdict IS NOT NULL GROUP BY ALL),
seeds AS (SELECT host, kind, n / sum(n) OVER (PARTITION BY kind) AS seed FROM marks),
links AS (SELECT host AS src, {low.format('target')} AS dst, count(*) AS links FROM (SELECT host, unnest(regexp_extract_all(html, '{link}', 1, 'i')) AS target FROM cut) WHERE host <> '' AND target <> '' AND host <> {low.format('target')} GROUP BY ALL),
both_ways AS (SELECT src AS a, dst AS b, 'trust' AS kind, links FROM links UNION ALL SELECT dst, src, 'distrust', links FROM links),
moves AS (SELECT a, b, kind, links / sum(links) OVER (PARTITION BY a, kind) AS share FROM both_ways), {steps},
hosts AS (SELECT host, coalesce(sum(score) FILTER (WHERE kind = 'trust'), 0) AS trust, coalesce(sum(score) FILTER (WHERE kind = 'distrust'), 0) AS distrust FROM s{rounds} GROUP BY host)
SELECT page_id, host, path, rule, coalesce(verdict, CASE WHEN coalesce(distrust, 0) > {threshold} * (coalesce(trust, 0) + coalesce(distrust, 0)) THEN 'block' ELSE 'allow' END) AS verdict, coalesce(trust, 0)::DOUBLE AS trust, coalesce(distrust, 0)::DOUBLE AS distrust
FROM ruled LEFT JOIN hosts USING (host)"""


# base32 of a hex digest: five hex digits make four letters
WARC = """WITH p AS (SELECT page_id, coalesce(html, '') AS html, sha1(coalesce(html, '')) AS hex FROM pages), f AS (SELECT *, min(page_id) OVER (PARTITION BY html) AS first FROM p),
g AS (SELECT *, list_transform(range(8), lambda i: ('0x' || substr(hex, i::INT * 5 + 1, 5))::BIGINT) AS parts FROM f)
SELECT page_id, strlen(html)::BIGINT AS payload_bytes,
 list_aggregate(list_transform(parts, lambda n: 'ABCDEFGHIJKLMNOPQRSTUVWXYZ234567'[n // 32768 + 1] || 'ABCDEFGHIJKLMNOPQRSTUVWXYZ234567'[(n // 1024) % 32 + 1] || 'ABCDEFGHIJKLMNOPQRSTUVWXYZ234567'[(n // 32) % 32 + 1] || 'ABCDEFGHIJKLMNOPQRSTUVWXYZ234567'[n % 32 + 1]), 'string_agg', '') AS payload_digest,
 CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id = first THEN NULL ELSE first END AS refers_to FROM g"""


# sums in the order of dimensions, as doubles; a query never meets itself
SEARCH = """WITH e AS (SELECT vec_id, min(embedding::DOUBLE[]) AS v FROM embeddings WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0 GROUP BY vec_id),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_reduce(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2]), lambda a, b: a + b) AS score FROM e q JOIN e c ON q.vec_id % 20 = 0 AND q.vec_id <> c.vec_id AND len(q.v) = len(c.v))
SELECT query_id, rank::INT AS rank, vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 20"""
