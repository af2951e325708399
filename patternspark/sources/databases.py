"""The itemset databases of the experiments, built from the given tables, each with SQL for its (tid, item) pairs."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.itemdb import ItemDB, build_item_db
from .bins import Bins
from .itemize import ItemRule, itemize_attributes, itemize_baskets, itemize_signs, itemize_words

#: Six worked transactions over the letters A to P (fixed values).
ILLUSTRATION = ("AEGKN", "CEHLN", "ADHJO", "BDHJN", "ADHJNP", "AEGKNP")
ALPHABET = "ABCDEFGHIJKLMNOP"
#: Sixteen fixed tokens.
TOKENS = "en in the on of and to a is be as that it er re was".split()
DISC, TAX = Bins((0.035, 0.075), ("lo", "mid", "hi")), Bins((0.025, 0.055), ("lo", "mid", "hi"))
QTY = Bins((18, 35), ("lo", "mid", "hi"))
BALANCE = Bins((1000, 4000, 7000), ("a", "b", "c", "d"))
LENGTH = Bins((1000, 2000, 4000), ("s", "m", "l", "x"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def illus(spark: SparkSession, sf_dir: str = "") -> DataFrame:
    return spark.createDataFrame([(t, list(x)) for t, x in enumerate(ILLUSTRATION, 1)], "tid long, items array<string>")


def line_attr(spark: SparkSession, sf_dir: str, collapse: bool = False) -> DataFrame:
    rules = [ItemRule("rf", "l_returnflag"), ItemRule("ls", "l_linestatus"), ItemRule("qty", "l_quantity", QTY), ItemRule("disc", "l_discount", DISC), ItemRule("tax", "l_tax", TAX)]
    return itemize_attributes(table(spark, sf_dir, "lineitem"), F.monotonically_increasing_id(), rules, collapse=collapse)


def order_attr(spark: SparkSession, sf_dir: str, collapse: bool = False) -> DataFrame:
    rules = [ItemRule("st", "o_orderstatus"), ItemRule("pr", "o_orderpriority"), ItemRule("yr", F.year("o_orderdate")), ItemRule("val", F.floor(F.col("o_totalprice") / 125000).cast("long"))]
    return itemize_attributes(table(spark, sf_dir, "orders"), "o_orderkey", rules, collapse=collapse)


def _lines(spark: SparkSession, sf_dir: str, *cols: str) -> DataFrame:
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", *[c for c in cols if c.startswith("l_")])
    part = table(spark, sf_dir, "part").select("p_partkey", *[c for c in cols if c.startswith("p_")])
    return line.join(part, line.l_partkey == part.p_partkey)


def order_brand(spark: SparkSession, sf_dir: str) -> DataFrame:
    return itemize_baskets(_lines(spark, sf_dir, "p_brand"), "l_orderkey", "p_brand")


def order_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = _lines(spark, sf_dir, "p_type", "l_returnflag", "l_linestatus")
    item = F.explode(F.array(F.concat(F.lit("type="), "p_type"), F.concat(F.lit("rf="), "l_returnflag"), F.concat(F.lit("ls="), "l_linestatus")))
    return itemize_baskets(lines.select("l_orderkey", item.alias("item")), "l_orderkey", "item")


def user_day(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = table(spark, sf_dir, "events")
    return itemize_baskets(ev, (F.col("user_id") * 1000 + F.dayofyear("ts")).cast("long"), "event_type")


def emb_sign8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return itemize_signs(table(spark, sf_dir, "embeddings"), "vec_id", "embedding", 8)


def emb_sign16(spark: SparkSession, sf_dir: str) -> DataFrame:
    return itemize_signs(table(spark, sf_dir, "embeddings"), "vec_id", "embedding", 16)


def doc_words16(spark: SparkSession, sf_dir: str) -> DataFrame:
    return itemize_words(table(spark, sf_dir, "documents"), "doc_id", "text", TOKENS)


def part_attr(spark: SparkSession, sf_dir: str, collapse: bool = False) -> DataFrame:
    rules = [ItemRule("ty", "p_type"), ItemRule("sz", F.floor((F.col("p_size") - 1) / 10).cast("long")), ItemRule("pr", "p_retailprice", Bins.threshold(950, "lo", "hi"))]
    return itemize_attributes(table(spark, sf_dir, "part"), "p_partkey", rules, collapse=collapse)


def cust_attr(spark: SparkSession, sf_dir: str, collapse: bool = False) -> DataFrame:
    rules = [ItemRule("nat", F.col("c_nationkey") % 5), ItemRule("seg", "c_mktsegment"), ItemRule("bal", "c_acctbal", BALANCE)]
    return itemize_attributes(table(spark, sf_dir, "customer"), "c_custkey", rules, collapse=collapse)


def label_attr(spark: SparkSession, sf_dir: str, collapse: bool = False) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars")
    both = docs.join(table(spark, sf_dir, "labels"), "doc_id")
    rules = [ItemRule("lang", "lang"), ItemRule("q", "quality"), ItemRule("tox", "toxic"), ItemRule("len", "n_chars", LENGTH)]
    return itemize_attributes(both, "doc_id", rules, collapse=collapse)


def _bins_sql(col: str, bins: Bins) -> str:
    return "case " + " ".join(f"when {col} < {e} then '{x}'" for e, x in zip(bins.edges, bins.labels)) + f" else '{bins.labels[-1]}' end"


def _rows_sql(source: str, tid: str, parts: list[str]) -> str:
    return f"select tid, unnest([{', '.join(parts)}]) as item from (select {tid} as tid, * from {source})"


_DIMS = lambda d: ", ".join(f"'d{k:02d}' || case when embedding[{k}] > 0 then '+' else '-' end" for k in range(1, d + 1))
_TOKEN_LIST = ", ".join(f"'{t}'" for t in TOKENS)

#: (tid, item) pairs, without repeats.
LONG_SQL: dict[str, str] = {
    "illus": "select tid, unnest(string_split(s, '')) as item from (values " + ", ".join(f"({k}, '{x}')" for k, x in enumerate(ILLUSTRATION, 1)) + ") v(tid, s)",
    "line_attr": _rows_sql("lineitem", "row_number() over ()", ["'rf=' || l_returnflag", "'ls=' || l_linestatus", "'qty=' || " + _bins_sql("l_quantity", QTY), "'disc=' || " + _bins_sql("l_discount", DISC), "'tax=' || " + _bins_sql("l_tax", TAX)]),
    "order_attr": _rows_sql("orders", "o_orderkey", ["'st=' || o_orderstatus", "'pr=' || o_orderpriority", "'yr=' || year(o_orderdate)", "'val=' || floor(o_totalprice / 125000)::bigint"]),
    "order_brand": "select distinct l_orderkey as tid, p_brand as item from lineitem join part on l_partkey = p_partkey",
    "order_mix": "select distinct l_orderkey as tid, unnest(['type=' || p_type, 'rf=' || l_returnflag, 'ls=' || l_linestatus]) as item from lineitem join part on l_partkey = p_partkey",
    "user_day": "select distinct user_id * 1000 + dayofyear(ts) as tid, event_type as item from events",
    "emb_sign8": f"select vec_id as tid, unnest([{_DIMS(8)}]) as item from embeddings",
    "emb_sign16": f"select vec_id as tid, unnest([{_DIMS(16)}]) as item from embeddings",
    "doc_words16": f"select doc_id as tid, unnest(list_intersect([{_TOKEN_LIST}], list_distinct(regexp_extract_all(lower(text), '[a-z]+')))) as item from documents",
    "part_attr": _rows_sql("part", "p_partkey", ["'ty=' || p_type", "'sz=' || ((p_size - 1) // 10)", "'pr=' || case when p_retailprice < 950 then 'lo' else 'hi' end"]),
    "cust_attr": _rows_sql("customer", "c_custkey", ["'nat=' || (c_nationkey % 5)", "'seg=' || c_mktsegment", "'bal=' || " + _bins_sql("c_acctbal", BALANCE)]),
    "label_attr": _rows_sql("(select * from documents join labels using (doc_id))", "doc_id", ["'lang=' || lang", "'q=' || quality", "'tox=' || toxic", "'len=' || " + _bins_sql("n_chars", LENGTH)]),
}
#: Rows of a database where that is not the number of distinct tids.
COUNT_SQL = {"doc_words16": "select count(*) from documents"}

BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (illus, line_attr, order_attr, order_brand, order_mix, user_day, emb_sign8, emb_sign16, doc_words16, part_attr, cust_attr, label_attr)
}
#: Databases of attributes: one transaction a row.
ATTRIBUTES = ("line_attr", "order_attr", "part_attr", "cust_attr", "label_attr")


def _values(df: DataFrame, **cols: str) -> DataFrame:
    """``item``: each distinct value of the columns behind its prefix."""
    items = F.array(*[F.concat(F.lit(prefix), F.col(c).cast("string")) for c, prefix in cols.items()])
    return df.select(*cols).distinct().select(F.explode(items).alias("item"))


#: Items of basket databases as their tables list them, without the baskets; some may be in no basket.
LISTED: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "order_brand": lambda s, d: _values(table(s, d, "part"), p_brand=""),
    "order_mix": lambda s, d: _values(table(s, d, "part"), p_type="type=").union(_values(table(s, d, "lineitem"), l_returnflag="rf=", l_linestatus="ls=")),
    "user_day": lambda s, d: _values(table(s, d, "events"), event_type=""),
}


def transactions(spark: SparkSession, sf_dir: str, name: str, **form: bool) -> DataFrame:
    return BUILDERS[name](spark, sf_dir, **form)


def item_db(spark: SparkSession, sf_dir: str, name: str, *, collapse: bool = True, theta: float | int | None = None) -> ItemDB:
    tx = transactions(spark, sf_dir, name, **({"collapse": True} if collapse and name in ATTRIBUTES else {}))
    listed = LISTED[name](spark, sf_dir) if name in LISTED else None
    return build_item_db(tx, alphabet=list(ALPHABET) if name == "illus" else None, collapse=collapse, theta=theta, listed=listed)
