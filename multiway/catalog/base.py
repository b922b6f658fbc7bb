"""Registration of queries beside their SQL, and tensors that several queries share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..operators.tensors import CooTensor
from ..sources import tables

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return add


_built: dict[tuple, tuple] = {}


def built(spark: SparkSession, sf_dir: str, name: str) -> tuple[CooTensor, dict[str, DataFrame]]:
    """A tensor of a table, built once for an application and folder (it lies stored in the shared folder)."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _built:
        facts, modes, value = getattr(tables, name)(spark, sf_dir)
        large = [n for n, _ in modes if n in ("part", "supplier", "customer", "user")]
        t, d = tables.from_table(facts, modes, value, "count" if name in ("orders_four", "activity") else "sum", large)
        _built[key] = (t.kept(), d)
    return _built[key]


def encoded_sql(keyed: str, modes: list[str]) -> str:
    """WITH-parts `keyed` and `t` (cells) of a tensor in SQL."""
    ranks = ", ".join(f"dense_rank() OVER (ORDER BY {m}) - 1 AS i{k + 1}" for k, m in enumerate(modes))
    return f"keyed AS ({keyed}), t AS (SELECT {ranks}, v FROM keyed)"


NBM = encoded_sql("SELECT s_nationkey AS nation, p_brand AS brand, strftime(l_shipdate, '%Y-%m') AS month, sum(l_quantity) AS v FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey GROUP BY ALL", ["nation", "brand", "month"])
FIVE = encoded_sql("SELECT c_nationkey AS nation, p_brand AS brand, c_mktsegment AS segment, o_orderpriority AS priority, year(l_shipdate) AS y, sum(l_quantity) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey GROUP BY ALL", ["nation", "brand", "segment", "priority", "y"])
FOUR = encoded_sql("SELECT c_nationkey AS nation, c_mktsegment AS segment, o_orderpriority AS priority, o_orderstatus AS status, CAST(count(*) AS DOUBLE) AS v FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL", ["nation", "segment", "priority", "status"])
PSC = encoded_sql("SELECT l_partkey AS part, l_suppkey AS supplier, o_custkey AS customer, sum(l_quantity) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL", ["part", "supplier", "customer"])
UTE = encoded_sql("SELECT user_id AS u, event_type AS e, hour(ts) AS h, CAST(count(*) AS DOUBLE) AS v FROM events GROUP BY ALL", ["u", "e", "h"])
