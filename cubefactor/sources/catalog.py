"""The tensors that the given tables hold, each as a DataFrame recipe and as portable SQL."""

from __future__ import annotations

from dataclasses import dataclass
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.tensor import TensorFrame, encode, raw_cells
from .tables import load

_CACHE: dict[tuple[str, str, str], TensorFrame] = {}


@dataclass
class Recipe:
    n_modes: int
    build: Callable[[SparkSession, str], DataFrame]
    sql: str


def _month(column: str):
    return F.year(column) * 12 + F.month(column) - 1


def _orders_lines(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "orders").join(load(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))


def _purchases3(spark, sf):
    return raw_cells(_orders_lines(spark, sf), [F.col("o_custkey"), F.col("l_partkey"), _month("o_orderdate")], F.avg("l_quantity"))


def _purchases4(spark, sf):
    return raw_cells(_orders_lines(spark, sf), [F.col("o_custkey"), F.col("l_partkey"), _month("l_shipdate"), F.col("o_orderpriority")], F.avg("l_quantity"))


def _supply3(spark, sf):
    return raw_cells(load(spark, sf, "lineitem"), [F.col("l_suppkey"), F.col("l_partkey"), _month("l_shipdate")], F.avg("l_extendedprice"))


def _events(extra: list[str]):
    def build(spark, sf):
        keys = {
            "day": F.date_format("ts", "yyyy-MM-dd"),
            "hour": F.hour("ts"),
            "k": F.get_json_object("props", "$.k").cast("int"),
            "bin": F.floor(F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")) / 30).cast("int"),
        }
        return raw_cells(load(spark, sf, "events"), [F.col("user_id"), F.col("event_type"), *(keys[e] for e in extra)], F.log(1 + F.avg("value")))

    return build


def _geo5(spark, sf):
    star = _orders_lines(spark, sf).join(load(spark, sf, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    star = star.join(load(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(load(spark, sf, "part"), F.col("l_partkey") == F.col("p_partkey"))
    return raw_cells(star, [F.col("c_nationkey"), F.col("s_nationkey"), F.col("p_brand"), _month("o_orderdate"), F.col("o_orderpriority")], F.avg("l_quantity"))


def _tokens(table: str, keys: list[str], least: int):
    def build(spark, sf):
        words = load(spark, sf, table).select(*keys, F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("token")).where("token <> ''")
        cells = raw_cells(words, [*(F.col(k) for k in keys), F.col("token")], F.log(1 + F.count("*").cast("double")))
        if least <= 1:
            return cells
        last = f"k{len(keys) + 1}"
        wide = cells.groupBy(last).count().where(F.col("count") >= least).select(last)
        return cells.join(wide, last, "left_semi").select(*(f"k{n}" for n in range(1, len(keys) + 2)), "x")

    return build


def _embed2(spark, sf):
    return raw_cells(load(spark, sf, "embeddings").select("vec_id", F.posexplode("embedding").alias("pos", "e")), [F.col("vec_id"), F.col("pos")], F.avg(F.col("e").cast("double")))


def _pages3(spark, sf):
    pages = load(spark, sf, "pages").select(F.parse_url("url", F.lit("HOST")).alias("host"), F.split(F.parse_url("url", F.lit("PATH")), "/").alias("path"))
    return raw_cells(pages, [F.col("host"), F.get("path", F.lit(1)), F.get("path", F.lit(2))], F.count("*"))


def _labelled3(spark, sf):
    joined = load(spark, sf, "documents").join(load(spark, sf, "labels"), "doc_id")
    return raw_cells(joined, [F.col("lang"), F.col("source"), F.col("quality")], F.avg("toxic"))


_MONTH = "year({0}) * 12 + month({0}) - 1"


def _token_sql(table: str, keys: list[str], least: int) -> str:
    names = ", ".join(f"{k} AS k{n}" for n, k in enumerate(keys, 1))
    group = ", ".join(keys)
    last = f"k{len(keys) + 1}"
    cells = f"SELECT {names}, token AS {last}, ln(1 + CAST(count(*) AS DOUBLE)) AS x FROM (SELECT {group}, unnest(regexp_split_to_array(lower(text), '[^\\p{{L}}]+')) AS token FROM {table}) WHERE token <> '' GROUP BY {group}, token"
    return cells if least <= 1 else f"SELECT * FROM ({cells}) WHERE {last} IN (SELECT {last} FROM ({cells}) GROUP BY {last} HAVING count(*) >= {least})"


def _event_sql(extra: list[str]) -> str:
    keys = {"day": "strftime(ts, '%Y-%m-%d')", "hour": "hour(ts)", "k": "CAST(json_extract_string(props, '$.k') AS INT)", "bin": "CAST(floor(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) / 30) AS INT)"}
    every = ["user_id", "event_type", *(keys[e] for e in extra)]
    return f"SELECT {', '.join(f'{k} AS k{n}' for n, k in enumerate(every, 1))}, ln(1 + avg(value)) AS x FROM events GROUP BY {', '.join(every)}"


_JOIN = "FROM orders JOIN lineitem ON o_orderkey = l_orderkey"
RECIPES = {
    "purchases3": Recipe(3, _purchases3, f"SELECT o_custkey AS k1, l_partkey AS k2, {_MONTH.format('o_orderdate')} AS k3, avg(l_quantity) AS x {_JOIN} GROUP BY 1, 2, 3"),
    "purchases4": Recipe(4, _purchases4, f"SELECT o_custkey AS k1, l_partkey AS k2, {_MONTH.format('l_shipdate')} AS k3, o_orderpriority AS k4, avg(l_quantity) AS x {_JOIN} GROUP BY 1, 2, 3, 4"),
    "supply3": Recipe(3, _supply3, f"SELECT l_suppkey AS k1, l_partkey AS k2, {_MONTH.format('l_shipdate')} AS k3, avg(l_extendedprice) AS x FROM lineitem GROUP BY 1, 2, 3"),
    "events3": Recipe(3, _events(["hour"]), _event_sql(["hour"])),
    "events4": Recipe(4, _events(["day", "hour"]), _event_sql(["day", "hour"])),
    "events5": Recipe(5, _events(["day", "hour", "k"]), _event_sql(["day", "hour", "k"])),
    "events_bin30": Recipe(3, _events(["bin"]), _event_sql(["bin"])),
    "geo5": Recipe(5, _geo5, f"SELECT c_nationkey AS k1, s_nationkey AS k2, p_brand AS k3, {_MONTH.format('o_orderdate')} AS k4, o_orderpriority AS k5, avg(l_quantity) AS x {_JOIN} JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2, 3, 4, 5"),
    "tokens3": Recipe(3, _tokens("documents", ["lang", "source"], 8), _token_sql("documents", ["lang", "source"], 8)),
    "embed2": Recipe(2, _embed2, "SELECT vec_id AS k1, pos AS k2, avg(CAST(e AS DOUBLE)) AS x FROM (SELECT vec_id, unnest(range(len(embedding))) AS pos, unnest(embedding) AS e FROM embeddings) GROUP BY 1, 2"),
    "pages3": Recipe(3, _pages3, "SELECT * FROM (SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS k1, split_part(regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1), '/', 2) AS k2, split_part(regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1), '/', 3) AS k3, CAST(count(*) AS DOUBLE) AS x FROM pages GROUP BY 1, 2, 3)"),
    "turns3": Recipe(3, _tokens("conversations", ["conv_id", "role"], 1), _token_sql("conversations", ["conv_id", "role"], 1)),
    "labelled3": Recipe(3, _labelled3, "SELECT lang AS k1, source AS k2, quality AS k3, avg(toxic) AS x FROM documents JOIN labels USING (doc_id) GROUP BY 1, 2, 3"),
    "bench2": Recipe(2, _tokens("benchmark", ["item_id"], 1), _token_sql("benchmark", ["item_id"], 1)),
}


def tensor(spark: SparkSession, sf_dir: str, name: str) -> TensorFrame:
    """A tensor with dense indices; built once per application and folder."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _CACHE:
        recipe = RECIPES[name]
        _CACHE[key] = encode(recipe.build(spark, sf_dir), recipe.n_modes)
    return _CACHE[key]


def cells_sql(name: str) -> str:
    """SQL for the encoded cells (i1..iN, x)."""
    n = RECIPES[name].n_modes
    ranks = ", ".join(f"dense_rank() OVER (ORDER BY k{m}) - 1 AS i{m}" for m in range(1, n + 1))
    return f"SELECT {ranks}, CAST(x AS DOUBLE) AS x FROM ({RECIPES[name].sql}) WHERE x IS NOT NULL" + "".join(f" AND k{m} IS NOT NULL" for m in range(1, n + 1))
