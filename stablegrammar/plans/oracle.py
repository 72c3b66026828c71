"""DuckDB SQL of parsing rounds, unrolled as materialised CTEs."""

from __future__ import annotations

from stablegrammar.functions.hashing import HashFamily, make_family

DOCUMENTS = "SELECT doc_id AS string_id, text FROM documents"
BENCHMARK = "SELECT item_id AS string_id, text FROM benchmark"


def affine(x: str, h) -> str:
    return f"((({h.a} * ({x})::BIGINT + {h.b}) % {h.p}) % {h.m})"


def poly(fps: str, h) -> str:
    return affine(f"list_reduce(list_reverse({fps}), lambda acc, x: (acc * {h.c} + x) % {h.p}, 0::BIGINT)", h)


def symbols(source: str, family: HashFamily, coded: bool = False) -> str:
    """CTEs src and s0(string_id, pos, code, sym, fp, e); source has (string_id, text), or (string_id, pos, code) if `coded`."""
    chars = "SELECT string_id, unnest(range(1, length(text) + 1)) AS pos, unicode(unnest(string_split(text, ''))) AS code FROM src WHERE text <> ''"
    return f"""src AS MATERIALIZED ({source}),
c0 AS ({'SELECT * FROM src' if coded else chars}),
s0 AS MATERIALIZED (SELECT string_id, pos::BIGINT AS pos, code, code::VARCHAR AS sym, {affine('code', family[0])} AS fp, 1::BIGINT AS e FROM c0)"""


TYPES = """SELECT *, lag({by}) OVER w AS prev, first_value(stp IGNORE NULLS) OVER (PARTITION BY string_id ORDER BY pos ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS nxt
FROM (SELECT *, nullif(sign(lead({by}) OVER w - {by}), 0) AS stp FROM {seq} WINDOW w AS (PARTITION BY string_id ORDER BY pos)) WINDOW w AS (PARTITION BY string_id ORDER BY pos)"""


def round_ctes(i: int, family: HashFamily, types: str, is_break: str, active: bool) -> str:
    """CTEs a{i} (active symbols with breaks), p{i} (phrases), s{i}, and d{i} (roots of the level below); all strings count as active if not `active`."""
    more = "HAVING count(*) > 1" if active else ""
    return f"""n{i} AS (SELECT string_id FROM s{i - 1} GROUP BY string_id {more}),
d{i} AS MATERIALIZED (SELECT string_id, sym, e, {i - 1} AS level FROM s{i - 1} WHERE string_id NOT IN (SELECT string_id FROM n{i})),
x{i} AS (SELECT * FROM s{i - 1} WHERE string_id IN (SELECT string_id FROM n{i})),
t{i} AS ({types.format(by='fp', seq=f'x{i}')}),
a{i} AS MATERIALIZED (SELECT string_id, pos, sym, fp, e, coalesce({is_break}, false) AS brk FROM t{i}),
q{i} AS (SELECT *, 1 + sum(brk::INT) OVER (PARTITION BY string_id ORDER BY pos ROWS UNBOUNDED PRECEDING) AS no FROM a{i}),
p{i} AS MATERIALIZED (SELECT string_id, no::BIGINT AS pos, min(pos) AS start, count(*) AS len, md5('{i}:' || string_agg(sym, ',' ORDER BY pos)) AS sym, string_agg(sym, ',' ORDER BY pos) AS rhs, {poly('list(fp ORDER BY pos)', family[i])} AS fp, sum(e)::BIGINT AS e FROM q{i} GROUP BY string_id, no),
s{i} AS MATERIALIZED (SELECT string_id, pos, sym, fp, e FROM p{i})"""


def build(source: str, rounds: int, family: HashFamily | None = None, *, types: str = TYPES, is_break: str = "nxt > 0 AND prev > fp", active: bool = True, coded: bool = False) -> str:
    """WITH clause of so many rounds, by any break rule over the columns of `types`."""
    family = family or make_family()
    return "WITH " + ",\n".join([symbols(source, family, coded), *(round_ctes(i, family, types, is_break, active) for i in range(1, rounds + 1))])


def rules(rounds: int) -> str:
    """Distinct rules of all levels, as a subquery."""
    return " UNION ALL ".join(f"SELECT {i} AS level, sym, any_value(rhs) AS rhs, any_value(len) AS rhs_len, any_value(e) AS exp_len, any_value(fp) AS fp, count(*) AS uses FROM p{i} GROUP BY sym" for i in range(1, rounds + 1))


def roots(rounds: int) -> str:
    """Roots of all strings that end within so many rounds, empty ones included."""
    ends = " UNION ALL ".join(f"SELECT string_id, sym AS root_sym, level AS root_level, e AS n_symbols FROM d{i}" for i in range(1, rounds + 1))
    return ends + " UNION ALL SELECT string_id, NULL, -1, 0 FROM src WHERE text = ''"


def level_stats(source: str, rounds: int) -> str:
    return f"{build(source, rounds)} SELECT level, count(*) AS g_i, sum(rhs_len)::BIGINT AS size_i, sum(exp_len)::BIGINT AS exp_i FROM ({rules(rounds)}) GROUP BY level"
