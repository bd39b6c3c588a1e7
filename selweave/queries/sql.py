"""Oracle SQL as chained common table expressions over the evaluation views."""

from __future__ import annotations

from selweave.operators.workload import attribute_sets
from selweave.sources.views import VIEWS

NUMBERS = {"oyear", "syear", "lag_band", "price_band", "net_band", "partkey", "suppkey", "size", "qty", "price_c", "oquarter", "omonth", "user_id", "hr", "daypart", "dom", "dow", "vband", "char_band", "word_band", "quality", "toxic", "html_band", "turn", "len_band", "label", *(f"s{k}" for k in range(8))}


def attrs_of(view: str) -> list[str]:
    return list(VIEWS[view].attributes)


def u(text: str) -> str:
    return f"(CAST('0x' || substr(md5({text}), 1, 8) AS BIGINT) / 4294967296.0)"


def rnd(text: str, digits: int) -> str:
    """Rounded; lifted a little first, so that ties fall alike in both engines."""
    return f"round(({text}) * 1.000000001, {digits})"


def view(name: str) -> str:
    return f"v AS ({VIEWS[name].sql('duckdb')})"


def dictionary(name: str) -> str:
    parts = []
    for a in attrs_of(name):
        sort = f"CAST({a} AS DOUBLE)" if a in NUMBERS else "CAST(NULL AS DOUBLE)"
        parts.append(f"SELECT '{a}' AS attr, CAST({a} AS VARCHAR) AS value, {sort} AS sort, count(*) AS freq FROM v GROUP BY {a}")
    return "d AS (SELECT attr, CAST(row_number() OVER (PARTITION BY attr ORDER BY sort NULLS FIRST, value NULLS FIRST) - 1 AS INT) AS code, value, freq FROM (" + " UNION ALL ".join(parts) + ")), c AS (SELECT attr, CAST(count(*) AS INT) AS card FROM d GROUP BY attr)"


def codes(name: str) -> str:
    attrs = attrs_of(name)
    joins = " ".join(f"JOIN d d{k} ON d{k}.attr = '{a}' AND CAST(v.{a} AS VARCHAR) IS NOT DISTINCT FROM d{k}.value" for k, a in enumerate(attrs))
    return "t AS (SELECT " + ", ".join(f"d{k}.code AS {a}" for k, a in enumerate(attrs)) + f", count(*) AS mult FROM v {joins} GROUP BY " + ", ".join(f"d{k}.code" for k in range(len(attrs))) + ")"


def base(name: str) -> str:
    return "WITH " + ", ".join((view(name), dictionary(name), codes(name)))


def combo(name: str, total: int, seed: int = 42, tries: int = 3) -> str:
    rows = ", ".join(f"({k}, '{s}', {q})" for k, s, q in attribute_sets(attrs_of(name), total) if q)
    return (
        f"sets(k, attrs, quota) AS (VALUES {rows}), draws AS (SELECT k, attrs, quota, unnest(generate_series(1, quota * {tries})) AS draw FROM sets), "
        "longs AS (SELECT k, attrs, quota, draw, unnest(string_split(attrs, ',')) AS attr FROM draws), "
        f"valued AS (SELECT l.*, CAST(floor({u(f'''concat_ws('|', '{seed}', attrs, draw, attr)''')} * card) AS INT) AS code FROM longs l JOIN c USING (attr)), "
        "whole AS (SELECT k, attrs, quota, draw, string_agg(CAST(code AS VARCHAR), ',' ORDER BY attr) AS cell FROM valued GROUP BY ALL), "
        "firsts AS (SELECT k, attrs, quota, cell, min(draw) AS draw FROM whole GROUP BY ALL), "
        "placed AS (SELECT *, row_number() OVER (PARTITION BY attrs ORDER BY draw) AS place FROM firsts), "
        "ids AS (SELECT *, row_number() OVER (ORDER BY k, attrs, place) - 1 AS qid FROM placed WHERE place <= quota), "
        "w AS (SELECT qid, k, attrs, unnest(string_split(attrs, ',')) AS attr, CAST(unnest(string_split(cell, ',')) AS INT) AS lo FROM ids)"
    )


def combo_truth(name: str) -> str:
    attrs = sorted(attrs_of(name))
    named = "concat_ws(',', " + ", ".join(f"CASE WHEN grouping({a}) = 0 THEN '{a}' END" for a in attrs) + ")"
    cell = "concat_ws(',', " + ", ".join(f"CASE WHEN grouping({a}) = 0 THEN CAST({a} AS VARCHAR) END" for a in attrs) + ")"
    return f"cube AS (SELECT {named} AS attrs, {cell} AS cell, sum(mult) AS n FROM t GROUP BY CUBE ({', '.join(attrs)})), truth AS (SELECT qid, k, attrs, CAST(coalesce(n, 0) AS BIGINT) AS true_rows FROM ids LEFT JOIN cube USING (attrs, cell))"


INDEPENDENT = "total AS (SELECT sum(mult) AS n FROM t), est AS (SELECT qid, CASE WHEN min(freq) <= 0 THEN 0 ELSE exp(sum(ln(freq / n))) * any_value(n) END AS est_rows FROM w JOIN d ON w.attr = d.attr AND w.lo = d.code, total GROUP BY qid)"


def sampled(name: str, share: float = 0.01, seed: int = 42) -> str:
    attrs = attrs_of(name)
    key = ", ".join(attrs)
    return f"s AS (SELECT {key}, count(*) AS mult FROM (SELECT {key}, unnest(generate_series(1, mult)) AS copy FROM t) WHERE {u(f'''concat_ws('|', '{seed}', {key}, copy)''')} < {share} GROUP BY {key})"


def box(by: str, source: str = "errors") -> str:
    q = ", ".join(f"{rnd(f'quantile_cont(qerr, {p})', 4)} AS p{int(100 * p):02d}" for p in (0.05, 0.25, 0.5, 0.75, 0.95))
    return f"SELECT {by}, count(*) AS n, {q}, {rnd('avg(qerr)', 4)} AS mean, {rnd('max(qerr)', 4)} AS max FROM {source} GROUP BY {by}"


ERRORS = "errors AS (SELECT t1.*, est_rows, greatest(greatest(true_rows, 1.0) / greatest(est_rows, 1.0), greatest(est_rows, 1.0) / greatest(true_rows, 1.0)) AS qerr FROM truth t1 JOIN est USING (qid))"


def ranged(name: str, own: list[str], total: int, seed: int = 7) -> str:
    """Wide interval queries r(qid, lo_<a>, hi_<a>) and their true counts."""
    names = ", ".join(f"'{a}'" for a in own)
    attrs = attrs_of(name)
    wide = ", ".join(f"coalesce(max(CASE WHEN attr = '{a}' THEN lo END), 0) AS lo_{a}, coalesce(max(CASE WHEN attr = '{a}' THEN hi END), 1000000000) AS hi_{a}" for a in attrs)
    inside = " AND ".join(f"t.{a} BETWEEN r.lo_{a} AND r.hi_{a}" for a in attrs)
    x = lambda what: f"CAST(floor({u(f'''concat_ws('|', '{seed}', qid, attr, '{what}')''')} * card) AS INT)"
    return (
        f"b AS (SELECT range AS qid, 1 + range * {len(own)} // {total} AS k FROM range({total})), cross_ AS (SELECT qid, k, attr, card FROM b, c WHERE attr IN ({names})), "
        f"ranked AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY {u(f'''concat_ws('|', '{seed}', qid, attr, 'pick')''')}, attr) AS place FROM cross_), "
        f"w AS (SELECT qid, k, attr, least({x('a')}, {x('b')}) AS lo, greatest({x('a')}, {x('b')}) AS hi FROM ranked WHERE place <= k), "
        f"r AS (SELECT qid, any_value(k) AS k, {wide} FROM w GROUP BY qid), truth AS (SELECT r.qid, CAST(coalesce(sum(t.mult), 0) AS BIGINT) AS true_rows FROM r LEFT JOIN t ON {inside} GROUP BY r.qid)"
    )


def training(name: str, budget: int, seed: int = 42) -> str:
    """Training queries: all single predicates, then subsets of tuples drawn by frequency."""
    attrs = attrs_of(name)
    key = f"md5(concat_ws('|', '{seed}', {', '.join(attrs)}))"
    draw = lambda what: u(f"concat_ws('|', '{seed}', draw, '{what}')")
    each = " UNION ALL ".join(f"SELECT draw, size, {draw(a)} AS x, '{a}' AS attr, {a} AS code FROM hit" for a in attrs)
    return (
        f"singles AS (SELECT attr || '=' || code AS canon, 0 AS draw FROM d), rest AS (SELECT {budget} - count(*) AS n FROM d), "
        f"ladder AS (SELECT *, sum(mult) OVER (ORDER BY {key} ROWS UNBOUNDED PRECEDING) AS up FROM t), whole AS (SELECT sum(mult) AS total FROM t), "
        f"draws AS (SELECT draw, CAST(floor({draw('tuple')} * total) AS BIGINT) AS spot, CAST(2 + floor({draw('size')} * {len(attrs) - 1}) AS INT) AS size FROM range(1, 2 * {budget} + 1) r(draw), whole, rest WHERE draw <= 2 * n), "
        "hit AS (SELECT draws.draw, draws.size, ladder.* FROM draws JOIN ladder ON spot >= up - mult AND spot < up), "
        f"each AS ({each}), placed AS (SELECT *, row_number() OVER (PARTITION BY draw ORDER BY x, attr) AS place FROM each), "
        "more AS (SELECT draw, string_agg(attr || '=' || code, ',' ORDER BY attr || '=' || code) AS canon FROM placed WHERE place <= size GROUP BY draw), "
        "firsts AS (SELECT canon, min(draw) AS draw FROM more GROUP BY canon), kept AS (SELECT canon, draw, row_number() OVER (ORDER BY draw) AS r FROM firsts), "
        "every AS (SELECT canon, draw FROM singles UNION ALL SELECT canon, draw FROM kept, rest WHERE r <= n), "
        "ids AS (SELECT canon, row_number() OVER (ORDER BY draw, canon) - 1 AS qid FROM every), parts AS (SELECT qid, unnest(string_split(canon, ',')) AS x FROM ids) "
        "SELECT qid, string_split(x, '=')[1] AS attr, CAST(string_split(x, '=')[2] AS INT) AS lo, CAST(string_split(x, '=')[2] AS INT) AS hi FROM parts"
    )


def augmented(name: str, target: int, seed: int = 42) -> str:
    """A log w(qid, attr, lo) and new queries of its weights: every(qid, attr, lo, hi, in_workload)."""
    draw = lambda *what: u("concat_ws('|', " + f"'{seed}', draw, " + ", ".join(what) + ")")
    return (
        "log AS (SELECT qid, string_agg(attr || '=' || lo, ',' ORDER BY attr || '=' || lo) AS canon, count(*) AS k FROM w GROUP BY qid), "
        f"want AS (SELECT {target} - count(*) AS n FROM log), ks AS (SELECT k, count(*) AS c FROM log GROUP BY k), shares AS (SELECT k, c / sum(c) OVER () AS share FROM ks), "
        "steps AS (SELECT k, share, sum(share) OVER (ORDER BY k ROWS UNBOUNDED PRECEDING) AS up FROM shares), "
        "aw AS (SELECT c.attr, count(lo) / (SELECT count(*) FROM w) AS weight FROM c LEFT JOIN w USING (attr) GROUP BY c.attr), "
        "vc AS (SELECT d.attr, code, greatest(count(w.lo), 1) AS c FROM d LEFT JOIN w ON w.attr = d.attr AND w.lo = d.code GROUP BY d.attr, code), vw AS (SELECT attr, code, c / sum(c) OVER (PARTITION BY attr) AS weight FROM vc), "
        "vl AS (SELECT *, sum(weight) OVER (PARTITION BY attr ORDER BY code ROWS UNBOUNDED PRECEDING) AS up FROM vw), "
        f"drawn AS (SELECT draw, {draw(repr('k'))} AS x FROM range(1, 3 * {target} + 1) r(draw), want WHERE draw <= 3 * n), "
        "sized AS (SELECT draw, k FROM drawn JOIN steps ON x >= up - share AND x < up), "
        f"raced AS (SELECT draw, k, attr, row_number() OVER (PARTITION BY draw ORDER BY -ln(greatest({draw('attr', repr('race'))}, 1e-12)) / weight, attr) AS r FROM sized, aw WHERE weight > 0), "
        f"priced AS (SELECT p.draw, p.attr, code FROM (SELECT draw, attr, {draw('attr', repr('value'))} AS v FROM raced WHERE r <= k) p JOIN vl ON vl.attr = p.attr AND v >= up - weight AND v < up), "
        "new AS (SELECT draw, string_agg(attr || '=' || code, ',' ORDER BY attr || '=' || code) AS canon FROM priced GROUP BY draw), "
        "fresh AS (SELECT canon, min(draw) AS draw FROM new WHERE canon NOT IN (SELECT canon FROM log) GROUP BY canon), numbered AS (SELECT canon, row_number() OVER (ORDER BY draw) AS r FROM fresh), "
        "added AS (SELECT r + (SELECT max(qid) FROM w) AS qid, unnest(string_split(canon, ',')) AS x FROM numbered, want WHERE r <= n), "
        "every AS (SELECT qid, attr, lo, lo AS hi, true AS in_workload FROM w UNION ALL SELECT qid, string_split(x, '=')[1], CAST(string_split(x, '=')[2] AS INT), CAST(string_split(x, '=')[2] AS INT), false FROM added)"
    )


def naive(budget: int, m: int, seed: int = 42) -> str:
    x = lambda what: u(f"concat_ws('|', '{seed}', qid, attr, '{what}')")
    size = u(f"concat_ws('|', '{seed}', range, 'size')")
    return (
        f"b AS (SELECT range AS qid, CAST(1 + floor({size} * {m}) AS INT) AS k FROM range({budget})), "
        f"ranked AS (SELECT qid, k, attr, CAST(floor({x('value')} * card) AS INT) AS lo, row_number() OVER (PARTITION BY qid ORDER BY {x('pick')}, attr) AS r FROM b, c) "
        "SELECT qid, attr, lo, lo AS hi FROM ranked WHERE r <= k"
    )


def grid(own: list[str], budget: int, kind: str) -> str:
    """Estimates of range queries w(qid, attr, lo, hi) from a grid over some attributes."""
    per = max(1, int((budget / 8) ** (1 / len(own)) + 1e-9))
    names = ", ".join(f"'{a}'" for a in own)
    if kind == "width":
        starts = f"SELECT DISTINCT attr, card, card * k // least({per}, card) AS s FROM c, range({per}) r(k) WHERE attr IN ({names}) AND k < least({per}, card)"
    else:
        seen = "SELECT d.attr, card, code, coalesce(sum(freq) OVER (PARTITION BY d.attr ORDER BY code ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS seen, sum(freq) OVER (PARTITION BY d.attr) AS total FROM d JOIN c USING (attr)"
        starts = (
            f"SELECT DISTINCT attr, card, s FROM (SELECT attr, card, 0 AS s FROM c WHERE attr IN ({names}) UNION ALL "
            f"SELECT f.attr, f.card, min(f.code) FROM ({seen}) f, range(1, {per}) r(k) WHERE f.attr IN ({names}) AND k < least({per}, f.card) AND code > 0 AND seen >= total * k / least({per}, f.card) GROUP BY f.attr, f.card, k)"
        )
    cells = ", ".join(f"(SELECT max(b) FROM bounds WHERE attr = '{a}' AND s <= t.{a}) AS b_{a}" for a in own)
    shares = " ".join(f"JOIN f f{k} ON f{k}.attr = '{a}' AND f{k}.b = g.b_{a} AND f{k}.qid = q.qid" for k, a in enumerate(own))
    return (
        f"starts AS ({starts}), bounds AS (SELECT attr, s, coalesce(lead(s) OVER (PARTITION BY attr ORDER BY s), card) - 1 AS e, row_number() OVER (PARTITION BY attr ORDER BY s) - 1 AS b FROM starts), "
        f"g AS (SELECT {', '.join('b_' + a for a in own)}, sum(mult) AS n FROM (SELECT mult, {cells} FROM t) GROUP BY ALL), q AS (SELECT DISTINCT qid FROM w), "
        "f AS (SELECT q.qid, bounds.attr, b, greatest(0, least(coalesce(hi, e), e) - greatest(coalesce(lo, s), s) + 1) / (e - s + 1) AS f FROM q CROSS JOIN bounds LEFT JOIN w ON w.qid = q.qid AND w.attr = bounds.attr), "
        f"est AS (SELECT q.qid, sum(n * {' * '.join(f'f{k}.f' for k in range(len(own)))}) AS est_rows FROM q CROSS JOIN g {shares} GROUP BY q.qid)"
    )
