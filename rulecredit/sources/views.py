"""Wide views: one row per tuple, one STRING column per attribute; null means no element.

Fixed cuts, so that any engine bins alike. Only the used columns reach the scans.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rulecredit.sources.tables import table


def _text(c: Column) -> Column:
    return c.cast("string")


def _ladder(c: Column, cuts: list[float]) -> Column:
    """Number of cuts at or below the value, as text."""
    out = F.lit("0")
    for i, cut in enumerate(cuts, 1):
        out = F.when(c >= cut, str(i)).otherwise(out)
    return F.when(c.isNotNull(), out)


def v_conversations(spark: SparkSession, folder: str) -> DataFrame:
    t = table(spark, folder, "conversations")
    n = F.length("text")
    return t.select(
        F.col("role"),
        _text(F.least("turn", F.lit(3))).alias("turn"),
        F.when(n < 100, "s").when(n < 300, "m").otherwise("l").alias("len"),
        _text(F.instr("text", "?") > 0).alias("qm"),
        _text(F.instr("text", "\n") > 0).alias("nl"),
    )


def v_documents(spark: SparkSession, folder: str) -> DataFrame:
    d = table(spark, folder, "documents").select("doc_id", "text", "lang", "source", "n_chars")
    both = d.join(table(spark, folder, "labels"), "doc_id", "left")
    has = lambda s: _text(F.instr("text", s) > 0)
    return both.select(
        F.col("lang"),
        _ladder(F.col("n_chars"), [300, 1500, 5000]).alias("nc"),
        F.col("source"),
        _text(F.col("quality")).alias("q"),
        _text(F.col("toxic")).alias("t"),
        has("http").alias("hu"),
        has("@").alias("em"),
        has("|").alias("pi"),
    )


def v_events(spark: SparkSession, folder: str) -> DataFrame:
    e = table(spark, folder, "events")
    return e.select("ts", *event_attributes())


def event_attributes() -> list[Column]:
    return [
        F.col("event_type").alias("et"),
        _text(F.floor(F.hour("ts") / 6)).alias("h"),
        _text(F.dayofweek("ts")).alias("dow"),
        _ladder(F.col("value"), [20, 50]).alias("v"),
        _text(F.floor(F.col("user_id") / 50)).alias("u"),
        _text(F.floor(F.get_json_object("props", "$.k").cast("int") / 25)).alias("k"),
    ]


def v_pages(spark: SparkSession, folder: str) -> DataFrame:
    p = table(spark, folder, "pages")
    has = lambda s: _text(F.instr("html", s) > 0)
    return p.select(
        F.substring_index("url", ":", 1).alias("sch"),
        F.regexp_extract("html", 'lang="([a-z]+)"', 1).alias("hl"),
        has("<table").alias("tb"),
        has("<script").alias("sc"),
        has("<nav").alias("nav"),
        _text(F.least(F.floor(F.length("html") / 1500), F.lit(3))).alias("len"),
    )


def v_embeddings(spark: SparkSession, folder: str, dims: int = 8) -> DataFrame:
    e = table(spark, folder, "embeddings")
    cell = lambda i: F.floor((F.get("embedding", F.lit(i)).cast("double") + 0.3) / 0.2)
    return e.select(
        _text(F.col("label")).alias("lab"),
        *[_text(F.least(F.greatest(cell(i), F.lit(0)), F.lit(2))).alias(f"x{i + 1}") for i in range(dims)],
    )


def _star(spark: SparkSession, folder: str) -> DataFrame:
    """lineitem with its order, customer, nation, region and part.

    Nation and region have fixed sizes and are broadcast; Spark picks the other
    joins by size.
    """
    li = table(spark, folder, "lineitem")
    o = table(spark, folder, "orders").select("o_orderkey", "o_custkey", "o_orderstatus")
    c = table(spark, folder, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    n = table(spark, folder, "nation").join(F.broadcast(table(spark, folder, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    p = table(spark, folder, "part").select("p_partkey", "p_type", "p_size", "p_retailprice")
    return (
        li.join(o, F.col("l_orderkey") == F.col("o_orderkey"))
        .join(c, F.col("o_custkey") == F.col("c_custkey"))
        .join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
        .join(p, F.col("l_partkey") == F.col("p_partkey"))
    )


def v_star(spark: SparkSession, folder: str) -> DataFrame:
    return _star(spark, folder).select(
        F.col("l_returnflag").alias("rf"),
        F.col("l_linestatus").alias("ls"),
        _text(F.floor(F.col("l_quantity") / 17)).alias("q"),
        _text(F.floor(F.least(F.col("l_extendedprice"), F.lit(99999.0)) / 35000)).alias("ep"),
        F.col("o_orderstatus").alias("os"),
        F.col("c_mktsegment").alias("seg"),
        F.col("r_name").alias("reg"),
        F.col("n_name").alias("nat"),
        F.col("p_type").alias("pt"),
        _text(F.floor((F.col("p_size") - 1) / 17)).alias("ps"),
        _text(F.floor((F.col("p_retailprice") - 900) / 34)).alias("pr"),
    )


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "conversations": v_conversations,
    "documents": v_documents,
    "events": lambda s, d: v_events(s, d).drop("ts"),
    "pages": v_pages,
    "embeddings": v_embeddings,
    "embeddings_wide": lambda s, d: v_embeddings(s, d, 64),
    "star": v_star,
}


@dataclass(frozen=True)
class Raw:
    """A wide table before binning: its key, the columns that get bins, and those that are values already."""

    frame: Callable[[SparkSession, str], DataFrame]
    key: tuple[str, ...]
    numeric: tuple[str, ...]
    plain: tuple[str, ...]


def _raw_conversations(spark: SparkSession, folder: str) -> DataFrame:
    t = table(spark, folder, "conversations")
    return t.select("conv_id", "turn", "role", F.length("text").alias("len"), *[e.alias(n) for n, e in _signs("text", {"qm": "?", "nl": "\n"})])


def _signs(column: str, wanted: dict[str, str]) -> list[tuple[str, Column]]:
    return [(n, _text(F.instr(column, s) > 0)) for n, s in wanted.items()]


def _raw_documents(spark: SparkSession, folder: str) -> DataFrame:
    d = table(spark, folder, "documents").join(table(spark, folder, "labels"), "doc_id", "left")
    signs = [e.alias(n) for n, e in _signs("text", {"hu": "http", "em": "@", "pi": "|"})]
    return d.select("doc_id", F.col("n_chars").alias("nc"), "lang", "source", _text(F.col("quality")).alias("q"), _text(F.col("toxic")).alias("t"), *signs)


def _raw_events(spark: SparkSession, folder: str) -> DataFrame:
    e = table(spark, folder, "events")
    k = F.get_json_object("props", "$.k").cast("int")
    return e.select("event_id", F.col("value").alias("v"), F.col("user_id").alias("u"), k.alias("k"), F.hour("ts").alias("h"), F.col("event_type").alias("et"), _text(F.dayofweek("ts")).alias("dow"))


def _raw_pages(spark: SparkSession, folder: str) -> DataFrame:
    p = table(spark, folder, "pages")
    signs = [e.alias(n) for n, e in _signs("html", {"tb": "<table", "sc": "<script", "nav": "<nav"})]
    return p.select(
        "page_id", F.length("html").alias("len"), F.substring_index("url", ":", 1).alias("sch"), F.regexp_extract("html", 'lang="([a-z]+)"', 1).alias("hl"), *signs
    )


def _raw_embeddings(spark: SparkSession, folder: str) -> DataFrame:
    e = table(spark, folder, "embeddings")
    return e.select("vec_id", _text(F.col("label")).alias("lab"), *[F.get("embedding", F.lit(i)).cast("double").alias(f"x{i + 1}") for i in range(8)])


def _raw_star(spark: SparkSession, folder: str) -> DataFrame:
    wide = _star(spark, folder)
    return wide.select(
        "l_orderkey", "l_linenumber", F.col("l_quantity").alias("q"), F.col("l_extendedprice").alias("ep"), F.col("p_size").alias("ps"), F.col("p_retailprice").alias("pr"),
        F.col("l_returnflag").alias("rf"), F.col("l_linestatus").alias("ls"), F.col("o_orderstatus").alias("os"), F.col("c_mktsegment").alias("seg"),
        F.col("r_name").alias("reg"), F.col("n_name").alias("nat"), F.col("p_type").alias("pt"),
    )


#: Workloads of the evaluation set: the views' attributes, numeric ones unbinned.
RAW = {
    "conversations": Raw(_raw_conversations, ("conv_id", "turn"), ("turn", "len"), ("role", "qm", "nl")),
    "documents": Raw(_raw_documents, ("doc_id",), ("nc",), ("lang", "source", "q", "t", "hu", "em", "pi")),
    "events": Raw(_raw_events, ("event_id",), ("v", "u", "k", "h"), ("et", "dow")),
    "pages": Raw(_raw_pages, ("page_id",), ("len",), ("sch", "hl", "tb", "sc", "nav")),
    "embeddings": Raw(_raw_embeddings, ("vec_id",), tuple(f"x{i}" for i in range(1, 9)), ("lab",)),
    "star": Raw(_raw_star, ("l_orderkey", "l_linenumber"), ("q", "ep", "ps", "pr"), ("rf", "ls", "os", "seg", "reg", "nat", "pt")),
}


def with_previous_event(events: DataFrame, gap: str = "7 days") -> DataFrame:
    """Adds ``prev``: the type of the user's latest earlier event within ``gap`` (an as-of lookup on itself)."""
    own = Window.partitionBy("user_id").orderBy("ts", "event_id")
    last = F.lag(F.struct("ts", "event_type")).over(own)
    near = last["ts"] >= F.col("ts") - F.expr(f"interval {gap}")
    return events.withColumn("prev", F.when(near, last["event_type"]))
