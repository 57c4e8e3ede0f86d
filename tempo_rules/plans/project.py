"""The given tables as facts, by family. Every projection is plain enough for SQL to repeat it."""

from __future__ import annotations

from collections.abc import Callable, Iterable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.granule import Granule, Interval, granule_of, instant, micros, missing, ordinal
from ..sources.tables import table
from .kg import KnowledgeGraph

HOUR = 3_600_000_000
#: An `error` event is taken to last six hours.
FAULT = 6 * HOUR
FAMILY_OF_EVENT = {"view": "browse", "click": "browse", "signup": "deal", "purchase": "deal", "error": "fault"}


def _key(prefix: str, *cols) -> Column:
    return F.concat_ws(":", F.lit(prefix), *[F.col(c).cast("string") if isinstance(c, str) else c.cast("string") for c in cols])


def _fact(df: DataFrame, fid: Column, s: Column, p: Column | str, o: Column, time: Interval | None, src: str, kind: str = "res") -> DataFrame:
    none = missing()
    i = time or Interval(none, none)
    p = F.lit(p) if isinstance(p, str) else p
    return df.select(fid.alias("fact_id"), s.alias("s"), p.alias("p"), o.alias("o"), F.lit(kind).alias("o_kind"), *i.named(), F.lit(time is not None).alias("is_temporal"), F.lit(src).alias("src"))


def _point(at: Column) -> Interval:
    g = instant(at)
    return Interval(g, g)


def _orders(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").withColumn("at", micros(F.col("o_orderdate")))


def _lines(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").withColumn("at", micros(F.col("l_shipdate")))


def _events(spark: SparkSession, d: str) -> DataFrame:
    k = F.from_json("props", "k long")["k"]
    return table(spark, d, "events").withColumns({"at": micros(F.col("ts")), "k": k})


def placed_order(spark, d):
    return _fact(_orders(spark, d), _key("K1", "o_orderkey"), _key("C", "o_custkey"), "placed_order", _key("O", "o_orderkey"), _point(F.col("at")), "orders")


def ordered_with_priority(spark, d):
    pr, ts = F.col("o_orderpriority"), F.col("o_orderdate")
    day, month, year = (granule_of(ts, u) for u in ("day", "month", "year"))
    pick = lambda n: F.when(pr.isin("1-URGENT", "2-HIGH"), getattr(day, n)).when(pr == "3-MEDIUM", getattr(month, n)).when(pr == "5-LOW", getattr(year, n))
    end = Granule(pick("lo"), pick("hi"), pick("gran"))
    return _fact(_orders(spark, d), _key("K2", "o_orderkey"), _key("C", "o_custkey"), "ordered_with_priority", _key("PR", "o_orderpriority"), Interval(instant(F.col("at")), end), "orders", "lit")


def ordered_on(spark, d):
    return _fact(_orders(spark, d), _key("K3", "o_orderkey"), _key("O", "o_orderkey"), "ordered_on", _key("ST", "o_orderstatus"), _point(F.col("at")), "orders", "lit")


def active_as(spark, d):
    span = _orders(spark, d).groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.min("at").alias("a"), F.max("at").alias("b"))
    joined = span.join(table(spark, d, "customer").select("c_custkey", "c_mktsegment"), "c_custkey")
    return _fact(joined, _key("K4", "c_custkey"), _key("C", "c_custkey"), "active_as", _key("SEG", "c_mktsegment"), Interval(instant(F.col("a")), instant(F.col("b"))), "orders", "lit")


def contains_part(spark, d):
    return _fact(_lines(spark, d), _key("K5", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "at"), _key("O", "l_orderkey"), "contains_part", _key("P", "l_partkey"), _point(F.col("at")), "lineitem")


def supplied_by(spark, d):
    return _fact(_lines(spark, d), _key("K6", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "at"), _key("O", "l_orderkey"), "supplied_by", _key("S", "l_suppkey"), _point(F.col("at")), "lineitem")


def supplier_active(spark, d):
    span = _lines(spark, d).groupBy(F.col("l_suppkey").alias("s_suppkey")).agg(F.min("at").alias("a"), F.max("at").alias("b"))
    joined = span.join(table(spark, d, "supplier").select("s_suppkey", "s_nationkey"), "s_suppkey")
    return _fact(joined, _key("K7", "s_suppkey"), _key("S", "s_suppkey"), "supplier_active", _key("N", "s_nationkey"), Interval(instant(F.col("a")), instant(F.col("b"))), "lineitem")


def in_state(spark, d):
    w = Window.partitionBy("user_id").orderBy("at", "event_id")
    ev = _events(spark, d).withColumn("next", F.lead("at").over(w)).withColumn("day", F.expr("at div 86400000000"))
    end = F.when(F.col("event_type") == "error", F.col("at") + FAULT).otherwise(F.col("next"))
    return _fact(ev, _key("K8", "event_id"), _key("UD", "user_id", "day"), "in_state", _key("EV", "event_type"), Interval(instant(F.col("at")), instant(end)), "events")


def did(spark, d):
    return _fact(_events(spark, d).where("k is not null"), _key("K9", "event_id"), _key("U", "user_id"), "did", _key("K", "k"), _point(F.col("at")), "events")


def by_event_type(spark, d):
    return _fact(_events(spark, d).where("k is not null"), _key("K10", "event_id"), _key("U", "user_id"), F.col("event_type"), _key("K", "k"), _point(F.col("at")), "events")


def said(spark, d):
    c = table(spark, d, "conversations")
    g = ordinal(F.col("turn"))
    return _fact(c, _key("K11", "conv_id", "turn"), _key("V", "conv_id"), F.concat(F.lit("said_"), F.col("role")), _key("T", "conv_id", "turn"), Interval(g, g), "conversations")


def catalogue_statics(spark, d):
    c, s, n, p = (table(spark, d, t) for t in ("customer", "supplier", "nation", "part"))
    return (
        _fact(c, _key("K12", F.lit("c"), "c_custkey"), _key("C", "c_custkey"), "in_nation", _key("N", "c_nationkey"), None, "customer")
        .unionByName(_fact(s, _key("K12", F.lit("s"), "s_suppkey"), _key("S", "s_suppkey"), "in_nation", _key("N", "s_nationkey"), None, "supplier"))
        .unionByName(_fact(n, _key("K12", F.lit("n"), "n_nationkey"), _key("N", "n_nationkey"), "in_region", _key("R", "n_regionkey"), None, "nation"))
        .unionByName(_fact(p, _key("K12", F.lit("t"), "p_partkey"), _key("P", "p_partkey"), "made_as", _key("PT", "p_type"), None, "part"))
        .unionByName(_fact(p, _key("K12", F.lit("b"), "p_partkey"), _key("P", "p_partkey"), "branded", _key("B", "p_brand"), None, "part"))
    )


def text_statics(spark, d):
    docs, pages, labels, vecs = (table(spark, d, t) for t in ("documents", "pages", "labels", "embeddings"))
    host = F.regexp_extract("url", "://([^/?#]+)", 1)
    return (
        _fact(docs, _key("K13", F.lit("l"), "doc_id"), _key("D", "doc_id"), "has_lang", _key("L", "lang"), None, "documents")
        .unionByName(_fact(docs, _key("K13", F.lit("s"), "doc_id"), _key("D", "doc_id"), "from_source", _key("SRC", "source"), None, "documents"))
        .unionByName(_fact(pages, _key("K13", F.lit("h"), "page_id"), _key("W", "page_id"), "on_host", _key("H", host), None, "pages"))
        .unionByName(_fact(labels, _key("K13", F.lit("q"), "doc_id"), _key("D", "doc_id"), "labelled", _key("Q", "quality"), None, "labels", "lit"))
        .unionByName(_fact(vecs, _key("K13", F.lit("v"), "vec_id"), _key("E", "vec_id"), "vec_label", _key("VL", "label"), None, "embeddings", "lit"))
    )


def sparse_statics(spark, d):
    """Very many static properties: one for each decile, language or source."""
    docs = table(spark, d, "documents")
    k = _events(spark, d).where("k is not null")
    return (
        _fact(k, _key("K14", "event_id"), _key("U", "user_id"), F.concat(F.lit("touched_"), F.expr("k div 10").cast("string")), _key("K", "k"), None, "events")
        .unionByName(_fact(docs, _key("K15", "doc_id"), _key("D", "doc_id"), F.concat_ws("_", F.lit("doc"), "lang", "source"), _key("L", "lang"), None, "documents"))
    )


FAMILIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "K1": placed_order, "K2": ordered_with_priority, "K3": ordered_on, "K4": active_as, "K5": contains_part, "K6": supplied_by, "K7": supplier_active,
    "K8": in_state, "K9": did, "K10": by_event_type, "K11": said, "K12": catalogue_statics, "K13": text_statics, "K14": sparse_statics,
}

#: Graphs that stand in for those of the experiments.
SMALL = ("K2", "K8", "K11")
WIDE = tuple(f"K{i}" for i in range(1, 14))
SPARSE = ("K1", "K8", "K11", "K13", "K14")
ORDERS = ("K1", "K2", "K3", "K4", "K5", "K6", "K7", "K12")


def facts(spark: SparkSession, sf_dir: str, families: Iterable[str] = WIDE) -> DataFrame:
    out = None
    for f in families:
        one = FAMILIES[f](spark, sf_dir)
        out = one if out is None else out.unionByName(one)
    return out


def classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """entity, class; an entity may have several classes."""
    t = lambda n: table(spark, sf_dir, n)
    region = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    pick = lambda df, e, c: df.select(e.alias("entity"), c.alias("class"))
    events = F.create_map(*[F.lit(x) for kv in FAMILY_OF_EVENT.items() for x in kv])
    ev = _events(spark, sf_dir)
    parts = [
        pick(t("customer"), _key("C", "c_custkey"), _key("SEG", "c_mktsegment")),
        pick(t("customer").join(region, F.col("c_nationkey") == F.col("n_nationkey")), _key("C", "c_custkey"), _key("R", "r_name")),
        pick(t("orders"), _key("O", "o_orderkey"), _key("ST", "o_orderstatus")),
        pick(t("part"), _key("P", "p_partkey"), _key("PT", "p_type")),
        pick(t("part"), _key("P", "p_partkey"), _key("B", "p_brand")),
        pick(t("supplier").join(region, F.col("s_nationkey") == F.col("n_nationkey")), _key("S", "s_suppkey"), _key("R", "r_name")),
        pick(ev.select("event_type").distinct(), _key("EV", "event_type"), F.try_element_at(events, F.col("event_type"))),
        pick(ev.where("k is not null").select("k").distinct(), _key("K", "k"), _key("KD", F.expr("k div 10"))),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.where("class is not null").distinct()


def graph(spark: SparkSession, sf_dir: str, families: Iterable[str] = WIDE) -> KnowledgeGraph:
    return KnowledgeGraph(facts(spark, sf_dir, families), classes(spark, sf_dir))


DAY = 24 * HOUR


def old_snapshot(new: DataFrame) -> DataFrame:
    """An earlier version with planted errors, by key: ends of K4 cut, ends of K8 two days late, system turns of K11 moved, second statuses in K3."""
    family, key = F.split_part("fact_id", F.lit(":"), F.lit(1)), F.expr("try_cast(split_part(fact_id, ':', 2) as long)")
    cut, late = (family == "K4") & (key % 97 == 0), (family == "K8") & (key % 97 == 0)
    moved = (family == "K11") & (key % 7 == 0) & (F.col("p") == "said_system")
    shift = F.when(cut, -30 * DAY).when(late, 2 * DAY).when(moved, 10).otherwise(0)
    begin = F.when(moved, 10).otherwise(0)
    out = new.withColumns({c: F.col(c) + shift for c in ("te_lo", "te_hi")} | {c: F.col(c) + begin for c in ("ts_lo", "ts_hi")})
    second = new.where((family == "K3") & (key % 97 == 0)).withColumns({"fact_id": F.concat(F.lit("K3x:"), key.cast("string")), "o": F.lit("ST:X")})
    return out.unionByName(second)
