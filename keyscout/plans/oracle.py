"""Generators of DuckDB SQL that answers the same questions by definition, independent of the method."""

from __future__ import annotations

from collections.abc import Sequence

#: column names and kinds of the given tables, in schema order
TABLES: dict[str, list[str]] = {
    "region": ["r_regionkey", "r_name"],
    "nation": ["n_nationkey", "n_name", "n_regionkey"],
    "customer": ["c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"],
    "supplier": ["s_suppkey", "s_name", "s_nationkey", "s_acctbal"],
    "part": ["p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"],
    "orders": ["o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"],
    "lineitem": ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"],
    "events": ["event_id", "ts", "user_id", "event_type", "value", "props"],
    "documents": ["doc_id", "text", "lang", "source", "n_chars"],
    "embeddings": ["vec_id", "embedding", "label"],
    "pages": ["page_id", "url", "html"],
    "benchmark": ["item_id", "text"],
    "labels": ["doc_id", "quality", "toxic"],
    "conversations": ["conv_id", "turn", "role", "text"],
}


def column_stats(source: str, columns: Sequence[str]) -> str:
    parts = [
        f"SELECT {i} AS col_ix, '{c}' AS col, count(*) AS cardinality, CAST(sum(n * (n - 1) // 2) AS DECIMAL(38,0)) AS agree_pairs, "
        f"max(n) AS longest_run, CAST(coalesce(sum(n) FILTER (WHERE v IS NULL), 0) AS BIGINT) AS nulls "
        f"FROM (SELECT {c} AS v, count(*) AS n FROM {source} GROUP BY 1)"
        for i, c in enumerate(columns)
    ]
    return " UNION ALL ".join(parts)


def column_types(source: str, columns: Sequence[str], factor: float) -> str:
    return f"SELECT s.*, agree_pairs <= (SELECT CAST(floor({factor} * count(*) * log2(count(*))) AS BIGINT) FROM {source}) AS covered FROM ({column_stats(source, columns)}) s"


def _mask(columns: Sequence[str]) -> str:
    return " + ".join(f"CASE WHEN a.{c} IS NOT DISTINCT FROM b.{c} THEN 0 ELSE {1 << i} END" for i, c in enumerate(columns))


def pair_masks(source: str, columns: Sequence[str], agree: Sequence[str]) -> str:
    """mask, pairs over all row pairs that agree on ``agree`` (all pairs for none)."""
    on = " AND ".join([*(f"a.{c} IS NOT DISTINCT FROM b.{c}" for c in agree), "a.rid < b.rid"])
    return f"WITH t AS (SELECT *, row_number() OVER () AS rid FROM {source}) SELECT CAST({_mask(columns)} AS BIGINT) AS mask, count(*) AS pairs FROM t a JOIN t b ON {on} GROUP BY 1"


def minimal(masks: str) -> str:
    """mask: those of ``masks`` (a query with a column mask) that contain no other one."""
    return f"WITH d AS (SELECT DISTINCT mask FROM ({masks})) SELECT mask FROM d a WHERE NOT EXISTS (SELECT 1 FROM d b WHERE (a.mask & b.mask) = b.mask AND a.mask <> b.mask)"


def hitting_sets(masks: str, m: int) -> str:
    """key_mask: minimal column sets that meet every mask."""
    return (
        f"WITH e AS (SELECT DISTINCT mask FROM ({masks})), h AS (SELECT range AS key_mask FROM range({1 << m}) WHERE NOT EXISTS (SELECT 1 FROM e WHERE (range & mask) = 0)) "
        "SELECT CAST(key_mask AS BIGINT) AS key_mask FROM h x WHERE NOT EXISTS (SELECT 1 FROM h y WHERE (x.key_mask & y.key_mask) = y.key_mask AND x.key_mask <> y.key_mask)"
    )


def _unique_sets(source: str, columns: Sequence[str]) -> str:
    """CTEs: sizes(mask) of every column set whose projections are all different."""
    m = len(columns)
    gid = f"GROUPING_ID({', '.join(columns)})"
    # GROUPING_ID has the first column in the highest bit, and 1 where it is not grouped
    mask = " + ".join(f"CASE WHEN (g >> {m - 1 - i}) & 1 = 0 THEN {1 << i} ELSE 0 END" for i in range(m))
    return (
        f"cubed AS (SELECT {gid} AS g, count(*) AS n FROM {source} GROUP BY CUBE ({', '.join(columns)})), "
        f"uniq AS (SELECT CAST({mask} AS BIGINT) AS mask FROM (SELECT g, max(n) AS n FROM cubed GROUP BY g) WHERE n = 1)"
    )


def _rendered(columns: Sequence[str], mask: str = "mask") -> str:
    return "concat_ws(',', " + ", ".join(f"CASE WHEN {mask} & {1 << i} <> 0 THEN '{c}' END" for i, c in enumerate(columns)) + ")"


def minimal_keys(source: str, columns: Sequence[str], prefix: str = "") -> str:
    """key, n_columns of every minimal key, by testing all column sets."""
    cte = f"WITH {prefix + ', ' if prefix else ''}{_unique_sets(source, columns)}"
    return (
        f"{cte} SELECT {_rendered(columns)} AS key, CAST(bit_count(mask) AS INTEGER) AS n_columns FROM uniq x "
        "WHERE NOT EXISTS (SELECT 1 FROM uniq y WHERE (x.mask & y.mask) = y.mask AND x.mask <> y.mask)"
    )


def keys_by_agreement(source: str, columns: Sequence[str], coarse: Sequence[str], prefix: str) -> str:
    """key, n_columns of every minimal key, for more columns than all sets of which can be grouped.

    A column set is no key if two rows agree on it.  Sets within the ``coarse`` columns (few values)
    are grouped one and all; any other set holds a fine column, and the rows that agree on it meet in
    a join on that column.
    """
    m, place = len(columns), {c: i for i, c in enumerate(columns)}
    cubed = f"SELECT GROUPING_ID({', '.join(coarse)}) AS g, max(n) AS n FROM (SELECT {', '.join(coarse)}, count(*) AS n FROM t GROUP BY ALL) GROUP BY CUBE ({', '.join(coarse)}) HAVING sum(n) > 1"
    low = " + ".join(f"CASE WHEN (g >> {len(coarse) - 1 - k}) & 1 = 0 THEN {1 << place[c]} ELSE 0 END" for k, c in enumerate(coarse))
    agree = " + ".join(f"CASE WHEN a.{c} IS NOT DISTINCT FROM b.{c} THEN {1 << i} ELSE 0 END" for i, c in enumerate(columns))
    parts = [f"SELECT DISTINCT {low} AS mask FROM ({cubed})"]
    parts += [f"SELECT DISTINCT {agree} AS mask FROM t a JOIN t b ON a.{c} IS NOT DISTINCT FROM b.{c} AND a.rid < b.rid" for c in columns if c not in coarse]
    less = " AND ".join(f"(key_mask & {1 << i} = 0 OR key_mask - {1 << i} NOT IN (SELECT key_mask FROM h))" for i in range(m))
    return (
        f"WITH {prefix}, t AS MATERIALIZED (SELECT *, row_number() OVER () AS rid FROM {source}), g AS MATERIALIZED (SELECT DISTINCT mask FROM ({' UNION ALL '.join(parts)})), "
        "top AS MATERIALIZED (SELECT mask FROM g x WHERE NOT EXISTS (SELECT 1 FROM g y WHERE (x.mask & y.mask) = x.mask AND x.mask <> y.mask)), "
        f"h AS MATERIALIZED (SELECT range AS key_mask FROM range({1 << m}) WHERE NOT EXISTS (SELECT 1 FROM top WHERE (range & mask) = range)) "
        f"SELECT {_rendered(columns, 'key_mask')} AS key, CAST(bit_count(key_mask) AS INTEGER) AS n_columns FROM h WHERE {less}"
    )


def short_keys(source: str, columns: Sequence[str], prefix: str) -> str:
    """key, n_columns of the minimal keys of one and two columns, for tables whose columns are unique but for two."""
    cells = " UNION ALL ".join(f"SELECT rid, {i} AS ix, '{c}' AS col, CAST({c} AS VARCHAR) AS v FROM t" for i, c in enumerate(columns))
    return (
        f"WITH {prefix}, t AS MATERIALIZED (SELECT *, row_number() OVER () AS rid FROM {source}), cells AS MATERIALIZED ({cells}), "
        "one AS (SELECT ix, col, count(DISTINCT v) = count(*) AS is_key FROM cells GROUP BY 1, 2), loose AS MATERIALIZED (SELECT cells.* FROM cells JOIN one USING (ix, col) WHERE NOT is_key), "
        "two AS (SELECT a.col || ',' || b.col AS key FROM loose a JOIN loose b ON a.rid = b.rid AND a.ix < b.ix GROUP BY a.col, b.col HAVING count(DISTINCT (a.v, b.v)) = count(*)) "
        "SELECT col AS key, CAST(1 AS INTEGER) AS n_columns FROM one WHERE is_key UNION ALL SELECT key, CAST(2 AS INTEGER) FROM two"
    )


def maximal_non_keys(source: str, columns: Sequence[str]) -> str:
    full = (1 << len(columns)) - 1
    return (
        f"WITH {_unique_sets(source, columns)}, bad AS (SELECT range AS mask FROM range({full + 1}) WHERE range NOT IN (SELECT mask FROM uniq)) "
        f"SELECT {_rendered(columns)} AS non_key, CAST(bit_count(mask) AS INTEGER) AS n_columns FROM bad x "
        "WHERE NOT EXISTS (SELECT 1 FROM bad y WHERE (x.mask & y.mask) = x.mask AND x.mask <> y.mask)"
    )


def conflict_groups(source: str, columns: Sequence[str]) -> str:
    names = ", ".join(columns)
    return f"SELECT {names}, count(*) AS cnt FROM {source} GROUP BY {names} HAVING count(*) > 1"
