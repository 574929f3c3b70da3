"""DuckDB SQL for the same integers: populations, reports, counters, queries, walks."""

from __future__ import annotations

from ldp_hist.functions.encoding import LETTERS
from ldp_hist.functions.randomizers import debias, keep_probability
from ldp_hist.functions.randomness import limit
from ldp_hist.plans.params import Params

LINE_KEY = "concat_ws(':', l_orderkey, l_linenumber, l_partkey, l_suppkey)"


def dig(tag: str, seed, *keys: str) -> str:
    head = f"'{seed}'" if isinstance(seed, int) else seed
    return f"sha256(concat_ws(':', '{tag}', {', '.join([head, *keys])}))"


def sl(d: str, start: int, length: int) -> str:
    return f"('0x' || substr({d}, {start}, {length}))::BIGINT"


def had(r: str, c: str) -> str:
    return f"(1 - 2 * (bit_count(({r})::BIGINT & ({c})::BIGINT) % 2))"


def sgn(d: str, at: int) -> str:
    return f"(1 - 2 * ({sl(d, at, 1)} % 2))"


def num(x: float) -> str:
    return f"CAST('{x!r}' AS DOUBLE)"


def flip(x: str, eps: float, phase: int, user: str = "user_key", key="'42'", kind: str = "binary", run: str | None = None) -> str:
    d = dig(f"coin{phase}", key, *([run] if run else []), user)
    return f"(CASE WHEN {sl(d, 1, 13)} < {limit(keep_probability(eps, kind))} THEN 1 ELSE -1 END * ({x}))"


def lines(item: str) -> str:
    return f"SELECT {LINE_KEY} AS user_key, ({item})::VARCHAR AS item FROM lineitem"


WORDS = """SELECT (doc_id * 1048576 + pos - 1)::VARCHAR AS user_key, item FROM (
  SELECT doc_id, unnest(w) AS item, generate_subscripts(w, 1) AS pos FROM (SELECT doc_id, regexp_extract_all(lower(text), '[a-z]+') AS w FROM documents))"""
U52 = f"({sl(dig('pow', 0, 'user_key'), 1, 13)} / 4503599627370496.0::DOUBLE)"
POWER = f"SELECT user_key, least(floor(100 * pow({U52}, {num(1 / 15)}))::INT, 99)::VARCHAR AS item FROM (SELECT {LINE_KEY} AS user_key FROM lineitem)"
_WORD = dig("word", 0, "item")
POPS = {
    "flag": lines("l_returnflag"), "status": lines("l_linestatus"), "line": lines("l_linenumber"), "quantity": lines("l_quantity::BIGINT"),
    "flagcode": lines("ascii(l_returnflag) - 65"),
    "priority": "SELECT o_orderkey::VARCHAR AS user_key, o_orderpriority AS item FROM orders",
    "segment": "SELECT c_custkey::VARCHAR AS user_key, c_mktsegment AS item FROM customer",
    "nation": "SELECT c_custkey::VARCHAR AS user_key, n_name AS item FROM customer JOIN nation ON c_nationkey = n_nationkey",
    "brand": f"SELECT {LINE_KEY} AS user_key, p_brand AS item FROM lineitem JOIN part ON l_partkey = p_partkey",
    "lang": "SELECT doc_id::VARCHAR AS user_key, lang AS item FROM documents",
    "event": "SELECT event_id::VARCHAR AS user_key, event_type AS item FROM events",
    "prop": "SELECT event_id::VARCHAR AS user_key, json_extract_string(props, '$.k') AS item FROM events",
    "toxic": "SELECT doc_id::VARCHAR AS user_key, toxic::VARCHAR AS item FROM labels",
    "host": "SELECT page_id::VARCHAR AS user_key, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS item FROM pages",
    "words": WORDS, "word6": f"SELECT user_key, rpad(substr(item, 1, 6), 6, '_') AS item FROM ({WORDS})",
    "powerlaw": POWER,
    "powerlaw6": "SELECT user_key, " + " || ".join(f"substr('abcdefghijklmnopqrstuvwxyz', ({sl(_WORD, 1 + 2 * i, 2)} % 26 + 1)::INT, 1)" for i in range(6)) + f" AS item FROM ({POWER})",
    "bench": """SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS item FROM benchmark""",
}


def exact(pop: str) -> str:
    return f"SELECT item, count(*)::BIGINT AS f FROM ({POPS[pop]}) GROUP BY item"


def draws(p: Params, seed: str = "", L: int = 1) -> str:
    """level, pair, row_, subset, col, cs from a column d."""
    return (f"({sl('d', 1, 8)} % {L} + 1)::INT AS level, ({sl('d', 9, 8)} % {p.t})::INT AS pair, {sl('d', 17, 8)} % {p.m} AS row_, "
            f"({sl('d', 25, 8)} % {p.R})::INT AS subset, {sl('d', 33, 8)} % {2 * p.T} AS col, {sgn('d', 41)} AS cs")


def own(p: Params, seed: str | None = None, L: int = 1) -> str:
    s = seed or f"'{p.seed}'"
    return f"SELECT *, {draws(p, L=L)} FROM (SELECT *, {dig('pub', s, 'user_key')} AS d FROM pop)"


def dictionary_ctes(pop: str, p: Params, where: str = "TRUE", seeds: str | None = None) -> str:
    """CTEs pop, rep, cnt, items, sums, est (item, est), by seed if ``seeds`` is given."""
    s, by, col = (f"'{p.seed}'", "", "") if not seeds else ("seed::VARCHAR", "seed, ", "seed,")
    source = f"SELECT * FROM ({POPS[pop]}) WHERE {where}" if not seeds else f"SELECT * FROM ({POPS[pop]}), (SELECT unnest({seeds}) AS seed)"
    y = flip(f"{sgn('hd', 9)} * {had('row_', f'{sl("hd", 1, 8)} % {p.m}')}", p.eps, 1, run=s if seeds else None)
    join = "c.pair = pl.pair" + (" AND c.seed = pl.seed" if seeds else "")
    return f"""pop AS MATERIALIZED ({source}),
rep AS (SELECT {by}pair, row_, {y} AS y FROM (SELECT *, {dig('pair', s, 'pair', 'item')} AS hd FROM ({own(p, s)}))),
cnt AS MATERIALIZED (SELECT {by}pair, row_, sum(y)::BIGINT AS s FROM rep GROUP BY ALL),
items AS (SELECT DISTINCT {col} item FROM pop),
places AS MATERIALIZED (SELECT {by}item, pair, {sl('hd', 1, 8)} % {p.m} AS h, {sgn('hd', 9)} AS g FROM (SELECT *, {dig('pair', s, 'pair', 'item')} AS hd FROM (SELECT {by}item, r.i AS pair FROM items, range({p.t}) r(i)))),
sums AS (SELECT {', '.join('pl.' + c for c in [*(['seed'] if seeds else []), 'item', 'pair'])}, coalesce(sum(c.s * pl.g * {had('c.row_', 'pl.h')}), 0)::BIGINT AS v FROM places pl LEFT JOIN cnt c ON {join} GROUP BY ALL),
est AS (SELECT {by}item, round({num(p.t * debias(p.eps))} * median(v), 4) AS est FROM sums GROUP BY ALL)"""


def dictionary(pop: str, p: Params, **how) -> str:
    return f"WITH {dictionary_ctes(pop, p, **how)} SELECT t.item, t.f, e.est FROM (SELECT item, count(*)::BIGINT AS f FROM pop GROUP BY item) t JOIN est e USING (item)"


def partitioned_ctes(pop_cte: str, p: Params, eps: float, phase: int = 1, items: str = "SELECT DISTINCT item FROM pop", name: str = "") -> str:
    """CTEs with the suffix ``name``: prep, pcnt, psums, pest (item, est). ``pop_cte`` is SQL giving user_key, item."""
    cell = f"{sl(dig('cell', p.seed, 'subset', 'item'), 1, 8)} % {p.T}"
    y = flip(f"{had(f'({cell}) + 1', 'col')} * cs", eps, phase)
    return f"""pown{name} AS (SELECT *, {draws(p)} FROM (SELECT *, {dig('pub', p.seed, 'user_key')} AS d FROM ({pop_cte}))),
pcnt{name} AS MATERIALIZED (SELECT subset, col, sum({y} * cs)::BIGINT AS s FROM pown{name} GROUP BY ALL),
pcells{name} AS MATERIALIZED (SELECT *, {cell} + 1 AS cell FROM (SELECT item, r.i AS subset FROM ({items}), range({p.R}) r(i))),
psums{name} AS (SELECT x.item, x.subset, coalesce(sum(c.s * {had('x.cell', 'c.col')}), 0)::BIGINT AS v FROM pcells{name} x LEFT JOIN pcnt{name} c ON c.subset = x.subset GROUP BY ALL),
pest{name} AS (SELECT item, round({num(p.R * debias(eps))} * median(v), 4) AS est FROM psums{name} GROUP BY item)"""


def text_code(item: str, levels: int) -> str:
    return " + ".join(f"((greatest(instr('{LETTERS}', substr(rpad(substr({item}, 1, {levels}), {levels}, '_'), {i + 1}, 1)), 1) - 1)::BIGINT << {5 * (levels - 1 - i)})" for i in range(levels))


def text_decode(code: str, levels: int) -> str:
    return " || ".join(f"substr('{LETTERS}', ((({code}) >> {5 * (levels - 1 - i)}) & 31)::INT + 1, 1)" for i in range(levels))


def tree_ctes(pop: str, p: Params, code: str, levels: int, bits: int, symbols: int, factor: float, beam: int | None = None) -> str:
    """CTEs pop, n, c1, c2, e1..eL (prefix, est), k0..kL (prefix), hist (code, est)."""
    hashed = [f"{dig('pair', p.seed, 'pair', x)}" for x in (f"concat_ws('.', level, (code >> ({bits} * ({levels} - level))::INT))", f"concat_ws('.', {levels}, code)")]
    ys = [flip(f"{sgn(h, 9)} * {had('row_', f'{sl(h, 1, 8)} % {p.m}')}", p.eps / 2, i + 1) for i, h in enumerate(("h1", "h2"))]
    out = [f"pop AS MATERIALIZED ({POPS[pop]})", "n AS (SELECT count(*) AS n FROM pop)",
           f"rep AS MATERIALIZED (SELECT level, pair, row_, {ys[0]} AS y1, {ys[1]} AS y2 FROM (SELECT *, {hashed[0]} AS h1, {hashed[1]} AS h2 FROM (SELECT *, ({code})::BIGINT AS code FROM ({own(p, L=levels)}))))",
           "c1 AS MATERIALIZED (SELECT level, pair, row_, sum(y1)::BIGINT AS s FROM rep GROUP BY ALL)", "c2 AS MATERIALIZED (SELECT pair, row_, sum(y2)::BIGINT AS s FROM rep GROUP BY ALL)", "k0 AS (SELECT 0::BIGINT AS prefix)"]

    def estimates(cands: str, level: int, table: str, scale: float, col: str) -> str:
        hd = dig("pair", p.seed, "pair", f"'{level}.' || {col}")
        return f"""SELECT {col}, round({num(scale)} * median(v), 4) AS est FROM (
  SELECT q.{col}, q.pair, coalesce(sum(c.s * q.g * {had('c.row_', 'q.h')}), 0)::BIGINT AS v FROM (
    SELECT {col}, pair, {sl('hd', 1, 8)} % {p.m} AS h, {sgn('hd', 9)} AS g FROM (SELECT *, {hd} AS hd FROM (SELECT {col}, r.i AS pair FROM ({cands}), range({p.t}) r(i)))) q
  LEFT JOIN {table} c ON c.pair = q.pair GROUP BY ALL) GROUP BY {col}"""

    a = debias(p.eps / 2)
    for level in range(1, levels + 1):
        cands = f"SELECT (k.prefix << {bits}) + s.i AS prefix FROM k{level - 1} k, range({symbols}) s(i)"
        out.append(f"e{level} AS MATERIALIZED ({estimates(cands, level, f'(SELECT * FROM c1 WHERE level = {level})', p.t * levels * a, 'prefix')})")
        keep = f"SELECT prefix FROM e{level} ORDER BY est DESC, prefix LIMIT {beam}" if beam else f"SELECT prefix FROM e{level}, n WHERE est >= {num(factor)} * sqrt(n)"
        out.append(f"k{level} AS MATERIALIZED ({keep})")
    out.append(f"hist AS MATERIALIZED ({estimates(f'SELECT prefix AS code FROM k{levels}', levels, 'c2', p.t * a, 'code')})")
    return ",\n".join(out)


def trace(levels: int) -> str:
    return " UNION ALL ".join(f"SELECT {i}::INT AS level, e.prefix, e.est, k.prefix IS NOT NULL AS kept FROM e{i} e LEFT JOIN k{i} k USING (prefix)" for i in range(1, levels + 1))


def bit_ctes(pop: str, p: Params, code: str, code_bit: str, length: int, repeats: int = 1, inner: int = 1) -> str:
    """CTEs pop (with code), best (rep, cell, bit, value, weight) of the bit-by-bit protocols; ``code_bit`` in terms of code, bit."""
    key = f"({sl(dig('hcell', p.seed, 'rep', 'code'), 1, 8)} % {p.T}) * 2 + ({code_bit})"
    y = flip(f"{had(f'{key} + 1', 'col')} * cs", p.eps / 2, 1)
    return f"""pop AS MATERIALIZED (SELECT *, ({code})::BIGINT AS code FROM ({POPS[pop]})),
bown AS (SELECT *, ({sl('d', 1, 8)} % {repeats})::INT AS rep, ({sl('d', 9, 8)} % {length})::INT AS bit, ({sl('d', 17, 8)} % {inner})::INT AS sub, {sl('d', 25, 8)} % {4 * p.T} AS col, {sgn('d', 33)} AS cs
  FROM (SELECT *, {dig('bits', p.seed, 'user_key')} AS d FROM pop)),
bcnt AS MATERIALIZED (SELECT rep, bit, sub, col, sum({y} * cs)::BIGINT AS s FROM bown GROUP BY ALL),
seen AS (SELECT DISTINCT rep, bit FROM bcnt),
bsum AS (SELECT q.rep, q.bit, q.sub, q.x, coalesce(sum(c.s * {had('q.x + 1', 'c.col')}), 0)::BIGINT AS v
  FROM (SELECT rep, bit, u.i AS sub, x.i AS x FROM seen, range({inner}) u(i), range({2 * p.T}) x(i)) q LEFT JOIN bcnt c ON c.rep = q.rep AND c.bit = q.bit AND c.sub = q.sub GROUP BY ALL),
bmed AS (SELECT rep, bit, (x // 2)::BIGINT AS cell, x % 2 AS b, median(v) AS est FROM bsum GROUP BY ALL),
best AS MATERIALIZED (SELECT rep, cell, bit, CASE WHEN max(est) FILTER (b = 1) > max(est) FILTER (b = 0) THEN 1 ELSE 0 END AS value, abs(max(est) FILTER (b = 1) - max(est) FILTER (b = 0)) AS weight FROM bmed GROUP BY ALL)"""


def experiment_ctes(source: str, eps: float, seeds: list[int], picks: str, t: int = 285, m: int | None = None) -> str:
    """CTEs pop, mm (m, n), f (item, f), picks, est (seed, item, est): repeated runs of the known-dictionary oracle, with m
    the power of two above sqrt(n) unless given. ``picks`` is SQL over f whose rows name the items that are asked for."""
    s = "seed::VARCHAR"
    y = flip(f"{sgn('hd', 9)} * {had('row_', f'{sl("hd", 1, 8)} % m')}", eps, 1, run=s)
    cells = str(m) if m else "(2 ** ceil(log2(greatest(1, sqrt(count(*))))))::BIGINT"
    return f"""pop AS MATERIALIZED ({source}), mm AS MATERIALIZED (SELECT {cells} AS m, count(*) AS n FROM pop),
f AS MATERIALIZED (SELECT item, count(*)::BIGINT AS f FROM pop GROUP BY item), picks AS MATERIALIZED ({picks}),
own AS (SELECT seed, user_key, item, m, ({sl('d', 9, 8)} % {t})::INT AS pair, {sl('d', 17, 8)} % m AS row_ FROM
  (SELECT *, {dig('pub', s, 'user_key')} AS d FROM pop, mm, (SELECT unnest({seeds}) AS seed))),
cnt AS MATERIALIZED (SELECT seed, pair, row_, sum({y})::BIGINT AS s FROM (SELECT *, {dig('pair', s, 'pair', 'item')} AS hd FROM own) GROUP BY ALL),
places AS MATERIALIZED (SELECT seed, item, pair, {sl('hd', 1, 8)} % m AS h, {sgn('hd', 9)} AS g FROM
  (SELECT *, {dig('pair', s, 'pair', 'item')} AS hd FROM (SELECT DISTINCT item FROM picks), mm, range({t}) r(pair), (SELECT unnest({seeds}) AS seed))),
sums AS (SELECT q.seed, q.item, q.pair, coalesce(sum(c.s * q.g * {had('c.row_', 'q.h')}), 0)::BIGINT AS v FROM places q LEFT JOIN cnt c ON c.seed = q.seed AND c.pair = q.pair GROUP BY ALL),
est AS (SELECT seed, item, round({num(t * debias(eps))} * median(v), 4) AS est FROM sums GROUP BY ALL)"""


def repeated(source: str, eps: float, seeds: list[int], picks: str, key: str, **how) -> str:
    return f"""(WITH {experiment_ctes(source, eps, seeds, picks, **how)}
SELECT p.{key}, p.item, round(any_value(f.f) / any_value(n)::DOUBLE, 6) AS share, round(avg(est / n::DOUBLE), 6) AS mean, round(stddev_samp(est / n::DOUBLE), 6) AS sd
FROM picks p JOIN f USING (item) JOIN est e ON e.item = p.item, mm GROUP BY p.{key}, p.item)"""


def tree_runs(pop: str, p: Params, code: str, levels: int, bits: int, symbols: int, factor: float, seeds: list[int]) -> str:
    """CTEs pop, n, hist (seed, code, est): one walk a seed."""
    s, a = "seed::VARCHAR", debias(p.eps / 2)
    hashed = [f"{dig('pair', s, 'pair', x)}" for x in (f"concat_ws('.', level, (code >> ({bits} * ({levels} - level))::INT))", f"concat_ws('.', {levels}, code)")]
    ys = [flip(f"{sgn(h, 9)} * {had('row_', f'{sl(h, 1, 8)} % {p.m}')}", p.eps / 2, i + 1, run=s) for i, h in enumerate(("h1", "h2"))]
    out = [f"pop AS MATERIALIZED ({POPS[pop]})", "n AS MATERIALIZED (SELECT count(*) AS n FROM pop)", f"seeds AS MATERIALIZED (SELECT unnest({seeds}) AS seed)",
           f"""rep AS MATERIALIZED (SELECT seed, level, pair, row_, sum({ys[0]})::BIGINT AS s1, sum({ys[1]})::BIGINT AS s2 FROM (SELECT *, {hashed[0]} AS h1, {hashed[1]} AS h2 FROM
  (SELECT *, ({code})::BIGINT AS code, {draws(p, L=levels)} FROM (SELECT *, {dig('pub', s, 'user_key')} AS d FROM pop, seeds))) GROUP BY seed, level, pair, row_)""",
           "c2 AS MATERIALIZED (SELECT seed, pair, row_, sum(s2)::BIGINT AS s FROM rep GROUP BY ALL)", "k0 AS (SELECT seed, 0::BIGINT AS prefix FROM seeds)"]

    def estimates(cands: str, level: int, table: str, scale: float, col: str) -> str:
        hd = dig("pair", s, "pair", f"'{level}.' || {col}")
        return f"""SELECT seed, {col}, round({num(scale)} * median(v), 4) AS est FROM (
  SELECT q.seed, q.{col}, q.pair, coalesce(sum(c.s * q.g * {had('c.row_', 'q.h')}), 0)::BIGINT AS v FROM (
    SELECT seed, {col}, pair, {sl('hd', 1, 8)} % {p.m} AS h, {sgn('hd', 9)} AS g FROM (SELECT *, {hd} AS hd FROM (SELECT seed, {col}, r.i AS pair FROM ({cands}), range({p.t}) r(i)))) q
  LEFT JOIN {table} c ON c.pair = q.pair AND c.seed = q.seed GROUP BY ALL) GROUP BY seed, {col}"""

    for level in range(1, levels + 1):
        cands = f"SELECT k.seed, (k.prefix << {bits}) + x.i AS prefix FROM k{level - 1} k, range({symbols}) x(i)"
        out.append(f"e{level} AS MATERIALIZED ({estimates(cands, level, f'(SELECT seed, pair, row_, s1 AS s FROM rep WHERE level = {level})', p.t * levels * a, 'prefix')})")
        out.append(f"k{level} AS MATERIALIZED (SELECT seed, prefix FROM e{level}, n WHERE est >= {num(factor)} * sqrt(n))")
    out.append(f"hist AS MATERIALIZED ({estimates(f'SELECT seed, prefix AS code FROM k{levels}', levels, 'c2', p.t * a, 'code')})")
    return ",\n".join(out)


def run_quality(ctes: str, decode: str, factor: float) -> str:
    return f"""WITH {ctes}, t AS MATERIALIZED (SELECT item, count(*)::BIGINT AS f FROM pop GROUP BY item), due AS (SELECT item FROM t, n WHERE f >= {num(factor)} * sqrt(n)),
hit AS (SELECT h.seed, count(*) AS listed, count(d.item) AS hit FROM (SELECT seed, {decode} AS item FROM hist) h LEFT JOIN due d USING (item) GROUP BY h.seed),
q AS (SELECT CASE WHEN listed > 0 THEN hit::DOUBLE / listed END AS precision, CASE WHEN (SELECT count(*) FROM due) > 0 THEN coalesce(hit, 0)::DOUBLE / (SELECT count(*) FROM due) END AS recall FROM seeds LEFT JOIN hit USING (seed))
SELECT count(*)::BIGINT AS runs, round(avg(precision), 6) AS precision, round(stddev_samp(precision), 6) AS precision_sd, round(avg(recall), 6) AS recall, round(stddev_samp(recall), 6) AS recall_sd FROM q"""
