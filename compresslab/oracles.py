"""SQL for DuckDB that states the answers of the queries over the same tables."""

from __future__ import annotations

from .plans import grids

TIERS = """
x AS (SELECT vec_id, unnest(range(len(embedding))) AS pos, unnest(embedding)::DOUBLE AS v FROM embeddings),
p AS (SELECT count(*) AS n, count(*) // 10 AS m, least(20, count(*) // 50) AS q FROM embeddings),
qv AS (SELECT vec_id % p.m AS query_id, pos, round(sum(v), 12) AS v FROM x, p WHERE vec_id % p.m < p.q GROUP BY ALL),
rel AS (SELECT vec_id % p.m AS query_id, vec_id AS item_id, 1 AS grade FROM embeddings, p WHERE vec_id % p.m < p.q)"""

WEIGHTED = """
wv AS (SELECT vec_id % p.m AS query_id, pos, round(sum(v * [3.0, 2.5, 2.0, 1.6, 1.3, 1.0, 0.8, 0.6, 0.5, 0.4][(vec_id // p.m)::INT + 1]), 12) AS v
       FROM x, p WHERE vec_id % p.m < p.q GROUP BY ALL)"""


def _levels(n: int) -> str:
    return "[" + ", ".join(str(i / n) for i in range(1, n)) + "]"


def calibration(source: str = "x", key: str = "") -> str:
    """Per-dimension statistics of a long table."""
    by = f"{key}, " if key else ""
    lists = ", ".join(f"list_transform(quantile_cont(v, {_levels(2**b)}), lambda e: round(e, 12)) AS pb{b}" for b in (2, 4, 8))
    return f"""cal AS (SELECT {by}pos, round(quantile_cont(v, 0.025), 12) AS lo, round(quantile_cont(v, 0.975), 12) AS hi, min(v) AS vmin, max(v) AS vmax,
 round(quantile_cont(v, 0.5), 12) AS med, {lists} FROM {source} GROUP BY ALL)"""


FORMATS = {"fp16": (10, -14, "65504", "'inf'::DOUBLE"), "bf16": (7, -126, "3.3895313892515355e38", "'inf'::DOUBLE"), "fp8_m3": (3, -6, "448", "NULL"), "fp8_m2": (2, -14, "57344", "'inf'::DOUBLE")}


def cast(form: str, v: str = "v") -> str:
    m, least, largest, _ = FORMATS[form]
    e = f"(CASE WHEN {v} = 0 THEN {least} ELSE greatest(floor(log2(abs({v}))), {least}) END)"
    step = f"pow(2.0, {e} - {m})"
    near = f"(round_even({v} / {step}, 0) * {step})"
    return f"(CASE WHEN abs({near}) > {largest} THEN sign({v}) * {largest} ELSE {near} END)"


def bins(bits: int, lo: str = "lo", hi: str = "hi") -> str:
    top = 2**bits
    return f"(CASE WHEN {hi} > {lo} THEN least(greatest(floor((least(greatest(v, {lo}), {hi}) - {lo}) / ({hi} - {lo}) * {top}), 0), {top - 1}) ELSE 0 END)"


def percentile(bits: int) -> str:
    return f"len(list_filter(pb{bits}, lambda e: e <= v))"


def expression(codec) -> tuple[str, str]:
    """(condition on pos, coordinate) of a codec in the space where cosines are taken."""
    from .operators import codecs as K

    if isinstance(codec, K.Truncate):
        inner = expression(codec.then)[1]
        return f"pos < {codec.keep}", inner
    if isinstance(codec, K.FloatCast):
        return "TRUE", cast(codec.form)
    if isinstance(codec, K.Bins):
        code = (bins(codec.width) if codec.clip else bins(codec.width, "vmin", "vmax")) if codec.equal_width else percentile(codec.width)
        if codec.scoring == "centred":
            code = f"({code} - {(2**codec.width - 1) / 2})"
        elif codec.scoring == "midpoint":
            code = f"(lo + ({code} + 0.5) * (hi - lo) / {2**codec.width})"
        return "TRUE", code
    if isinstance(codec, K.Binary):
        yes = f"(v > {'0' if codec.threshold == 'zero' else 'med'})"
        return "TRUE", f"({yes})::INT::DOUBLE" if codec.scoring == "raw" else f"(CASE WHEN {yes} THEN 1.0 ELSE -1.0 END)"
    return "TRUE", "v"


def scored(variants, items: str = "x", queries: str = "qv", item_id: str = "vec_id", extra: str = "") -> str:
    """CTEs up to scored(variant, query_id, item_id, score[, extra])."""
    tail = f", {extra}" if extra else ""
    code = " UNION ALL ".join(
        f"SELECT '{c.name}' AS variant, kind, id, pos, ({e})::DOUBLE AS c{tail} FROM a WHERE {w}" for c, (w, e) in ((c, expression(c)) for c in variants))
    extra_q = f", NULL AS {extra}" if extra else ""
    return f"""a AS (SELECT u.*, cal.* EXCLUDE (pos) FROM (SELECT 'i' AS kind, {item_id} AS id, pos, v{tail} FROM {items} UNION ALL SELECT 'q', query_id, pos, v{extra_q} FROM {queries}) u JOIN cal USING (pos)),
codes AS ({code}),
norms AS (SELECT variant, kind, id, sqrt(sum(c * c)) AS s FROM codes GROUP BY ALL),
dots AS (SELECT q.variant, q.id AS query_id, i.id AS item_id, sum(q.c * i.c) AS d{', i.' + extra if extra else ''} FROM codes q JOIN codes i ON q.variant = i.variant AND q.pos = i.pos WHERE q.kind = 'q' AND i.kind = 'i' GROUP BY ALL),
scored AS (SELECT dots.variant, query_id, item_id{tail}, round(CASE WHEN nq.s * ni.s > 0 THEN d / (nq.s * ni.s) ELSE 0 END, 9) AS score
  FROM dots JOIN norms nq ON nq.variant = dots.variant AND nq.kind = 'q' AND nq.id = query_id JOIN norms ni ON ni.variant = dots.variant AND ni.kind = 'i' AND ni.id = item_id)"""


def ranked(source: str = "scored", keys: str = "variant", name: str = "run", k: int = 100) -> str:
    by = f"{keys}, " if keys else ""
    return f"""{name} AS (SELECT * FROM (SELECT {by}query_id, item_id, score, row_number() OVER (PARTITION BY {by}query_id ORDER BY score DESC, item_id) AS rank FROM {source}) WHERE rank <= {k})"""


def measured(run: str = "run", keys: str = "variant", ks=(10, 100), rel: str = "rel", name: str = "measured", gain: str = "grade::DOUBLE") -> str:
    """name(keys, query_id, metric, k, value), rounded to 9 digits."""
    by = f"{keys}, " if keys else ""
    frame = f"(SELECT DISTINCT {keys} FROM {run}) f CROSS JOIN" if keys else ""
    on = " AND ".join(f"h.{k} = f.{k}" for k in keys.split(", ")) + " AND " if keys else ""
    fk = ", ".join(f"f.{k}" for k in keys.split(", ")) + ", " if keys else ""
    parts = []
    for k in ks:
        parts.append(f"""SELECT {fk}i.query_id, {k} AS k, i.relevant, coalesce(sum(1) FILTER (WHERE h.rank <= {k}), 0) AS hits, coalesce(sum(h.worth / log2(h.rank + 1)) FILTER (WHERE h.rank <= {k}), 0) AS dcg,
 min(h.rank) FILTER (WHERE h.rank <= {k}) AS first, any_value(i.i{k}) AS idcg FROM {frame} ideal_{name} i LEFT JOIN hits_{name} h ON {on}h.query_id = i.query_id GROUP BY ALL""")
    ideal = ", ".join(f"sum(part) FILTER (WHERE place <= {k}) AS i{k}" for k in ks)
    return f"""ideal_{name} AS (SELECT query_id, count(*) AS relevant, {ideal} FROM (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY grade DESC) AS place, {gain} / log2(row_number() OVER (PARTITION BY query_id ORDER BY grade DESC) + 1) AS part FROM {rel}) GROUP BY 1),
hits_{name} AS (SELECT r.*, {gain} AS worth FROM {run} r JOIN {rel} rel USING (query_id, item_id)),
sums_{name} AS ({' UNION ALL '.join(parts)}),
{name} AS (SELECT {by}query_id, 'recall' AS metric, k, round(hits / relevant, 9) AS value FROM sums_{name} UNION ALL SELECT {by}query_id, 'ndcg', k, round(dcg / idcg, 9) FROM sums_{name}
 UNION ALL SELECT {by}query_id, 'mrr', k, round(CASE WHEN first IS NULL THEN 0.0 ELSE 1.0 / first END, 9) FROM sums_{name})"""


def means(keys: str = "variant", source: str = "measured") -> str:
    by = f"{keys}, " if keys else ""
    return f"means AS (SELECT {by}metric, k, round(avg(value) * 100, 9) AS value FROM {source} GROUP BY ALL)"


def ratio_case(found: dict[str, float], name: str = "variant") -> str:
    return f"(CASE {name} " + " ".join(f"WHEN '{k}' THEN {v!r}" for k, v in found.items()) + " END)"


def grid_sql(variants, dims: int = 64, select: str = "") -> str:
    found = {c.name: round(c.ratio(dims), 6) for c in variants}
    return f"""WITH {TIERS}, {calibration()}, {scored(variants)}, {ranked()}, {measured()}, {means()}
SELECT variant, {ratio_case(found)}::DOUBLE AS ratio, metric, k, value FROM means {select}"""


def cutoffs() -> list[int]:
    return grids.cutoffs(64)
