"""Graphs from the given tables, each as Spark edges and as DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from biclique_spark.operators.graph import edges_from

_ORDER_LINES = "orders join lineitem on o_orderkey = l_orderkey"
#: Fixed forms: words are runs of letters of any script, links the targets of double-quoted href attributes.
_LETTERS, _HREF = r"[^\p{L}]+", r'href="([^"]*)"'


def _t(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def _lines(spark: SparkSession, sf: str) -> DataFrame:
    return _t(spark, sf, "orders").join(_t(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))


def words(df: DataFrame, id_col: str, text: str, most: float | None = None) -> DataFrame:
    """Distinct lower-case words of each row; with ``most``, only words that at most that share of rows have."""
    edges = edges_from(df.select(id_col, F.explode(F.split(F.lower(text), _LETTERS)).alias("w")).where("w <> ''"), id_col, "w")
    if most is None:
        return edges
    often = edges.groupBy("v").agg(F.count(F.lit(1)).alias("d")).where(F.col("d") > most * df.count()).select("v")
    return edges.join(often, "v", "left_anti")


def _top_components(df: DataFrame, n: int = 6) -> DataFrame:
    ranked = F.sort_array(F.transform("embedding", lambda x, i: F.struct((-F.abs(x)).alias("a"), i.alias("i"))))
    return edges_from(df.select("vec_id", F.explode(F.slice(ranked, 1, n)).alias("c")), "vec_id", F.col("c.i").cast("long"))


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "customer_part": lambda s, d: edges_from(_lines(s, d), "o_custkey", "l_partkey"),
    "customer_supplier": lambda s, d: edges_from(_lines(s, d), "o_custkey", "l_suppkey"),
    "supplier_part": lambda s, d: edges_from(_t(s, d, "lineitem"), "l_suppkey", "l_partkey"),
    "order_part": lambda s, d: edges_from(_t(s, d, "lineitem"), "l_orderkey", "l_partkey"),
    "order_supplier": lambda s, d: edges_from(_t(s, d, "lineitem"), "l_orderkey", "l_suppkey"),
    "nation_part": lambda s, d: edges_from(_lines(s, d).join(_t(s, d, "customer"), F.col("c_custkey") == F.col("o_custkey")), F.col("c_nationkey").cast("long"), "l_partkey"),
    "customer_brand": lambda s, d: edges_from(_lines(s, d).join(_t(s, d, "part"), F.col("p_partkey") == F.col("l_partkey")), "o_custkey", "p_brand"),
    "user_type": lambda s, d: edges_from(_t(s, d, "events"), "user_id", "event_type"),
    "user_k": lambda s, d: edges_from(_t(s, d, "events"), "user_id", F.get_json_object("props", "$.k").cast("long")),
    "user_hour": lambda s, d: edges_from(_t(s, d, "events"), "user_id", F.date_trunc("hour", "ts")),
    "doc_line": lambda s, d: edges_from(_t(s, d, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where("line <> ''"), "doc_id", "line"),
    "doc_token": lambda s, d: words(_t(s, d, "documents"), "doc_id", "text"),
    # For wedge joins: without the words that more than 5% of the documents hold.
    "doc_token_to_5_percent": lambda s, d: words(_t(s, d, "documents"), "doc_id", "text", 0.05),
    "conv_token": lambda s, d: words(_t(s, d, "conversations"), "conv_id", "text"),
    "item_token": lambda s, d: words(_t(s, d, "benchmark"), "item_id", "text"),
    "page_href": lambda s, d: edges_from(_t(s, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(_HREF), 1)).alias("href")), "page_id", "href"),
    "page_token": lambda s, d: words(_t(s, d, "pages").select("page_id", F.regexp_replace("html", "<[^>]*>", " ").alias("text")), "page_id", "text"),
    "doc_label": lambda s, d: edges_from(_t(s, d, "labels").select("doc_id", F.explode(F.array(F.concat(F.lit("quality="), "quality"), F.concat(F.lit("toxic="), "toxic"))).alias("fact")), "doc_id", "fact"),
    "vec_topdim": lambda s, d: _top_components(_t(s, d, "embeddings")),
}


def _sql_words(id_col: str, text: str, table: str) -> str:
    split = f"select {id_col}, unnest(regexp_split_to_array(lower({text}), '{_LETTERS}')) as w from {table}"
    return f"select distinct {id_col} as u, w as v from ({split}) where w <> '' and {id_col} is not null"


#: DuckDB SQL of edges(u, v) for the graphs that oracles use.
SQL: dict[str, str] = {
    "customer_part": f"select distinct o_custkey as u, l_partkey as v from {_ORDER_LINES}",
    "customer_supplier": f"select distinct o_custkey as u, l_suppkey as v from {_ORDER_LINES}",
    "supplier_part": "select distinct l_suppkey as u, l_partkey as v from lineitem",
    "order_part": "select distinct l_orderkey as u, l_partkey as v from lineitem",
    "order_supplier": "select distinct l_orderkey as u, l_suppkey as v from lineitem",
    "nation_part": f"select distinct c_nationkey::bigint as u, l_partkey as v from {_ORDER_LINES} join customer on c_custkey = o_custkey",
    "customer_brand": f"select distinct o_custkey as u, p_brand as v from {_ORDER_LINES} join part on p_partkey = l_partkey",
    "user_type": "select distinct user_id as u, event_type as v from events where event_type is not null",
    "user_k": "select distinct user_id as u, json_extract_string(props, '$.k')::bigint as v from events where json_extract_string(props, '$.k') is not null",
    "user_hour": "select distinct user_id as u, date_trunc('hour', ts) as v from events",
    "doc_line": "select distinct doc_id as u, line as v from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where line <> ''",
    "doc_token": _sql_words("doc_id", "text", "documents"),
    "conv_token": _sql_words("conv_id", "text", "conversations"),
    "item_token": _sql_words("item_id", "text", "benchmark"),
    "page_token": _sql_words("page_id", "regexp_replace(html, '<[^>]*>', ' ', 'g')", "pages"),
    "page_href": """select distinct page_id as u, href as v from (select page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) as href from pages)""",
    "doc_label": "select distinct doc_id as u, unnest(['quality=' || quality, 'toxic=' || toxic]) as v from labels",
    "vec_topdim": "select distinct vec_id as u, i::bigint - 1 as v from (select vec_id, i, row_number() over (partition by vec_id order by abs(x) desc, i) as r from (select vec_id, unnest(embedding) as x, generate_subscripts(embedding, 1) as i from embeddings)) where r <= 6",
}


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return BUILDERS[name](spark, sf_dir)
