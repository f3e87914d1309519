"""Formula tables derived from the given ones, by SQL that Spark and DuckDB read alike.

The given tables hold no formulas. Each carrier builds them from keys and values of a fact table: a workbook (customer,
supplier or user) holds sheets, sheets hold formulas.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def _s(x: str) -> str:
    return f"CAST({x} AS STRING)"


def _case(key: str, parts: list[str]) -> str:
    whens = " ".join(f"WHEN {i} THEN {p}" for i, p in enumerate(parts))
    return f"CASE ({key}) % {len(parts)} {whens} END"


_K, _C = "o_orderkey", "o_custkey"
_WHOLE = _s("CAST(floor(o_totalprice) AS BIGINT)")
_TEMPLATES = [
    f"'=SUM(A' || {_s(f'{_C} % 50 + 1')} || ':A' || {_s(f'{_C} % 50 + 9')} || ')'",
    f"'=IF(b' || {_s(f'{_K} % 90 + 1')} || '>' || {_WHOLE} || ',\"' || o_orderpriority || '\",\"\")'",
    f"'=VLookup($C' || {_s(f'{_K} % 40 + 1')} || ', ' || chr(39) || c_mktsegment || chr(39) || '!$A$1:$D$' || {_s(f'{_C} % 99 + 2')} || ', 3, FALSE)'",
    f"'=ROUND(' || {_s('CAST(o_totalprice AS DECIMAL(12,2))')} || '*D' || {_s(f'{_K} % 20 + 1')} || ',2)'",
    f"'=' || c_mktsegment || '!E' || {_s(f'{_K} % 30 + 1')} || '&\" ' || o_orderstatus || '\"'",
    f"'=IFERROR(F' || {_s(f'{_K} % 30 + 1')} || '/LOG10(G' || {_s(f'{_K} % 12 + 1')} || '),-' || {_s(f'{_C} % 9')} || ')'",
    f"'=COUNTIF(H1:H' || {_s(f'{_C} % 60 + 2')} || ',\"<>' || o_orderstatus || '\")'",
    f"'=EDATE(TODAY(),-' || {_s(f'{_K} % 36 + 1')} || ')'",
    f"'=AND(A' || {_s(f'{_K} % 25 + 1')} || '>0,OR(B' || {_s(f'{_C} % 25 + 1')} || '<=' || {_WHOLE} || ',C2<>\"' || c_mktsegment || '\"))'",
]
FORMULAS = f"""SELECT o_orderkey AS formula_id, o_custkey AS workbook_id, CAST(o_orderkey % 3 AS INT) AS sheet_no,
    {_case('o_orderkey', _TEMPLATES)} AS formula FROM orders JOIN customer ON o_custkey = c_custkey"""

_L = "l_orderkey * 10 + l_linenumber"
_WIDE = [
    f"'=SUMIF(A1:A' || {_s('l_suppkey % 90 + 2')} || ',\"' || p_name || '\",C1:C' || {_s('l_suppkey % 90 + 2')} || ')'",
    f"'=ROUND(' || {_s('CAST(l_extendedprice AS DECIMAL(12,2))')} || '*(1-E' || {_s('l_partkey % 40 + 1')} || '),2)'",
    f"'=IF(D' || {_s('l_orderkey % 60 + 1')} || '=\"' || p_brand || '\",' || {_s('CAST(floor(l_quantity) AS BIGINT)')} || ',0)'",
    f"'=INDEX($B$2:$B$' || {_s('l_partkey % 99 + 3')} || ',MATCH(\"' || p_type || '\",A:A,0))'",
    f"'=MAX(F' || {_s('l_orderkey % 30 + 1')} || ':F' || {_s('l_orderkey % 30 + 8')} || ')-MIN(G1:G9)'",
]
#: an id of order, line and a number among the rows that share both: one shuffle by order and line, no global sort
FORMULAS_WIDE = f"""SELECT (l_orderkey * 8 + l_linenumber) * 1000000 + row_number() OVER (PARTITION BY l_orderkey, l_linenumber
        ORDER BY l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS formula_id,
    l_suppkey AS workbook_id, l_returnflag AS sheet, {_case(_L, _WIDE)} AS formula
    FROM lineitem JOIN part ON l_partkey = p_partkey"""


def edits_sql(duck: bool) -> str:
    k = "json_extract_string(props, '$.k')" if duck else "get_json_object(props, '$.k')"
    name = "CASE event_type " + " ".join(f"WHEN '{e}' THEN '{f}'" for e, f in (("click", "COUNT"), ("view", "MAX"), ("purchase", "SUM"), ("signup", "MIN"), ("error", "AVERAGE"))) + " ELSE 'ABS' END"
    return f"""SELECT event_id, user_id AS workbook_id, ts, event_type AS sheet,
        '=' || {name} || '(B' || coalesce({k}, '1') || ')*' || {_s('CAST(floor(value) AS BIGINT)')} AS formula FROM events"""


def view(spark: SparkSession, sf_dir: str, *names: str) -> None:
    for n in names:
        spark.read.parquet(f"{sf_dir}/{n}.parquet").createOrReplaceTempView(n)


def dealt(rows: DataFrame, spark: SparkSession, fact: str, key: str = "formula_id") -> DataFrame:
    """The rows over all cores. A file of one row group is read by one task, whatever its rows cost afterwards; a fact table
    that comes in enough parts stays as it is."""
    wanted = 2 * spark.sparkContext.defaultParallelism
    return rows if spark.table(fact).rdd.getNumPartitions() >= wanted else rows.repartition(wanted, key)


def formulas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """formula_id, workbook_id, sheet_no, formula."""
    view(spark, sf_dir, "orders", "customer")
    return dealt(spark.sql(FORMULAS), spark, "orders")


def formulas_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """formula_id, workbook_id, sheet, formula."""
    view(spark, sf_dir, "lineitem", "part")
    return spark.sql(FORMULAS_WIDE)


def formula_edits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event_id, workbook_id, ts, sheet, formula."""
    view(spark, sf_dir, "events")
    return spark.sql(edits_sql(False))
