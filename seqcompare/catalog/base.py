"""Registration of queries with their DuckDB oracles, and SQL pieces that oracles share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.carriers import BASES, LETTERS

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

#: Null datasets of the registered tests: few, as their oracles make them too.
REPLICATES = 20
COHORTS = 16
#: Searches take as queries what has an id divisible by this.
ASKED = 100


def query(name: str, sql: str | None = None):
    def put(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def r(c: Column, places: int = 4) -> Column:
    """Rounded, and never a negative zero."""
    return F.round(c, places) + F.lit(0.0)


def rs(expression: str, places: int = 4) -> str:
    return f"round({expression}, {places}) + 0.0"


ACGT = f"translate(regexp_replace(lower(text), '[^a-z]', '', 'g'), '{LETTERS}', '{BASES}')"
ACGTN = f"translate(regexp_replace(lower(text), '[^a-z]+', 'N', 'g'), '{LETTERS}N', '{BASES}N')"
SYMBOL = "CASE event_type WHEN 'click' THEN 'C' WHEN 'view' THEN 'V' WHEN 'purchase' THEN 'P' WHEN 'signup' THEN 'S' WHEN 'error' THEN 'E' END"


def c1(encode: str = ACGT) -> str:
    return f"seq AS (SELECT CAST(doc_id AS VARCHAR) AS seq_id, {encode} AS residues FROM documents WHERE text IS NOT NULL)"


C5 = f"seq AS (SELECT lang || '/' || source AS seq_id, {ACGT} AS residues FROM documents WHERE text IS NOT NULL)"


def c4() -> str:
    return f"seq AS (SELECT CAST(user_id AS VARCHAR) AS seq_id, 0 AS part_id, string_agg({SYMBOL}, '' ORDER BY ts, event_id) AS residues FROM events GROUP BY user_id)"


#: Users' events in cohorts: a part for each user.
C4C = f"seq AS (SELECT 'c' || (user_id % {COHORTS}) AS seq_id, user_id AS part_id, string_agg({SYMBOL}, '' ORDER BY ts, event_id) AS residues FROM events GROUP BY user_id)"


def kmers(k: int, source: str = "seq", keys: str = "") -> str:
    return f"km AS (SELECT {keys}seq_id, substr(residues, i, {k}) AS feature FROM (SELECT {keys}seq_id, residues, unnest(range(1, length(residues) - {k} + 2)) AS i FROM {source}))"


def stat(k: int, keys: str = "", source: str = "seq") -> str:
    return kmers(k, source, keys) + f", stat AS (SELECT {keys}seq_id, feature, count(*) AS value FROM km GROUP BY ALL)"


WORDS = r"list_filter(string_split_regex(lower(text), '[^\p{L}]+'), lambda w: w <> '')"


def shingles(k: int) -> str:
    return f"toks AS (SELECT CAST(doc_id AS VARCHAR) AS seq_id, {WORDS} AS words FROM documents WHERE text IS NOT NULL), sh AS (SELECT seq_id, array_to_string(words[i:i + {k - 1}], ' ') AS feature FROM (SELECT seq_id, words, unnest(range(1, len(words) - {k} + 2)) AS i FROM toks)), stat AS (SELECT seq_id, feature, count(*) AS value FROM sh GROUP BY ALL)"


NATION = """stat AS (
SELECT n_name AS seq_id, 'c_mktsegment=' || c_mktsegment AS feature, count(*) AS value FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL UNION ALL
SELECT n_name, 'o_orderpriority=' || o_orderpriority, count(*) FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL UNION ALL
SELECT n_name, 'l_returnflag=' || l_returnflag, count(*) FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN part ON l_partkey = p_partkey GROUP BY ALL UNION ALL
SELECT n_name, 'p_brand=' || p_brand, count(*) FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN part ON l_partkey = p_partkey GROUP BY ALL)"""


def full_pairs(symbols: str = "ACGT", k: int = 4, keys: str = "", ordered: bool = True) -> str:
    """All pairs over the whole dictionary: x, y counts, p, q shares."""
    base = ", ".join(f"('{s}')" for s in symbols)
    tables = ", ".join(f"b b{i}" for i in range(k))
    word = " || ".join(f"b{i}.s" for i in range(k))
    on = "".join(f" AND a.{c.strip()} = c.{c.strip()}" for c in keys.split(",") if c.strip())
    partition = f"{keys}seq_id"
    return f"""b(s) AS (VALUES {base}), dict AS (SELECT {word} AS feature FROM {tables}),
ids AS (SELECT DISTINCT {partition} FROM stat),
whole AS (SELECT {', '.join('ids.' + c.strip() for c in partition.split(','))}, feature, CAST(coalesce(value, 0) AS DOUBLE) AS v FROM ids CROSS JOIN dict LEFT JOIN stat USING ({partition}, feature)),
shared AS (SELECT *, v / sum(v) OVER (PARTITION BY {partition}) AS p FROM whole),
pairs AS (SELECT {''.join('a.' + c.strip() + ', ' for c in keys.split(',') if c.strip())}a.seq_id AS i, c.seq_id AS j, a.feature, a.v AS x, c.v AS y, a.p AS p, c.p AS q FROM shared a JOIN shared c ON a.feature = c.feature AND a.seq_id < c.seq_id{on})"""


def searched(symbols: str = "ACGT", k: int = 4) -> str:
    """As ``full_pairs``, for each query (a name divisible by ``ASKED``) and every other sequence."""
    return full_pairs(symbols, k).replace("a.seq_id < c.seq_id", f"a.seq_id <> c.seq_id AND CAST(a.seq_id AS BIGINT) % {ASKED} = 0")


#: Values of the functions over all words, as SQL aggregates.
FUNCTION_SQL = {
    "d2": "sum(x * y)",
    "euclidean": "sqrt(sum((x - y) * (x - y)))",
    "sqeuclidean": "sum((x - y) * (x - y))",
    "manhattan": "sum(abs(x - y))",
    "canberra": "sum(CASE WHEN x + y > 0 THEN abs(x - y) / (x + y) ELSE 0 END)",
    "chisq": "sum(CASE WHEN x + y > 0 THEN (x - y) * (x - y) / (x + y) ELSE 0 END)",
    "sqchord": "sum((sqrt(x) - sqrt(y)) * (sqrt(x) - sqrt(y)))",
    "harmonic": "sum(CASE WHEN x + y > 0 THEN 2 * x * y / (x + y) ELSE 0 END)",
    "intersection": "sum(least(x, y))",
    "kulczynski2": "0.5 * (1 / sum(x) + 1 / sum(y)) * sum(least(x, y))",
    "jaccard": "sum(CASE WHEN x > 0 AND y > 0 THEN 1.0 ELSE 0 END) / sum(CASE WHEN x + y > 0 THEN 1.0 ELSE 0 END)",
    "jsd": "sum(CASE WHEN p > 0 THEN 0.5 * p * ln(2 * p / (p + q)) ELSE 0 END + CASE WHEN q > 0 THEN 0.5 * q * ln(2 * q / (p + q)) ELSE 0 END)",
    "cosine": "sum(x * y) / sqrt(sum(x * x) * sum(y * y))",
    "angle": "acos(least(sum(x * y) / sqrt(sum(x * x) * sum(y * y)), 1.0))",
    "containment": "sum(CASE WHEN x > 0 AND y > 0 THEN 1.0 ELSE 0 END) / sum(CASE WHEN x > 0 THEN 1.0 ELSE 0 END)",
    "minkowski3": "power(sum(abs(x - y) * abs(x - y) * abs(x - y)), 1.0 / 3)",
    "chebyshev": "max(abs(x - y))",
    "d2z": "sum((x - mx) * (y - my)) / (max(sx) * max(sy))",
    "jeffrey": "sum(((x + 1) / nx - (y + 1) / ny) * (ln((x + 1) / nx) - ln((y + 1) / ny)))",
}


def md5_number(text: str) -> str:
    return f"('0x' || substr(md5({text}), 1, 15))::BIGINT"


def bootstrap_sql(q: int, replicates: int, keys: str = "", each: int | None = None, name: str = "") -> str:
    """Tables pre, lens, grid, drawn, pieces and made (with ``name`` after each). ``each``: so many replicates to a seed, from 1 on."""
    seed = f"(1 + replicate // {each}) || '|' || " if each else "'1|' || "
    number = f"(replicate % {each})" if each else "replicate"
    key = "".join(f"{c.strip()} || '|' || " for c in keys.split(",") if c.strip())
    over = f"PARTITION BY {keys.rstrip(', ')} " if keys else ""
    on = "".join(f" AND drawn{name}.{c.strip()} = pre{name}.{c.strip()}" for c in keys.split(",") if c.strip())
    mine = "".join(f"drawn{name}.{c.strip()}, " for c in keys.split(",") if c.strip())
    total = f"JOIN (SELECT {keys}CAST(max(hi) AS BIGINT) AS total FROM pre{name} {'GROUP BY ' + keys.rstrip(', ') if keys else ''}) t {'USING (' + keys.rstrip(', ') + ')' if keys else 'ON true'}"
    range_of = md5_number("'range|' || seq_id")
    return f"""pre{name} AS (SELECT {keys}seq_id AS src, residues, length(residues) - {q} + 1 AS n, sum(length(residues) - {q} + 1) OVER ({over}ORDER BY {range_of} % 1024, seq_id, part_id) AS hi FROM seq WHERE length(residues) >= {q}),
lens{name} AS (SELECT {keys}seq_id, sum(length(residues)) AS len FROM seq GROUP BY ALL),
grid{name} AS (SELECT {keys}seq_id, len, replicate, unnest(range(0, CAST(ceil(len / {q}) AS BIGINT))) AS block FROM (SELECT {keys}seq_id, len, unnest(range(0, {replicates})) AS replicate FROM lens{name})),
drawn{name} AS (SELECT *, {md5_number(f"{seed}{key}{number} || '|' || seq_id || '|' || block")} % total AS address FROM grid{name} {total}),
pieces{name} AS (SELECT {mine}replicate, seq_id, len, block, substr(residues, CAST(address - (hi - n) + 1 AS BIGINT), {q}) AS piece FROM drawn{name} JOIN pre{name} ON address >= hi - n AND address < hi{on}),
made{name} AS (SELECT {keys}CAST(replicate AS INTEGER) AS replicate, seq_id, substr(string_agg(piece, '' ORDER BY block), 1, CAST(max(len) AS BIGINT)) AS residues FROM pieces{name} GROUP BY {keys}replicate, seq_id)"""
