"""Reading facts from files: quads in CSV or TSV, statements with qualifiers in JSON lines, N-Triples, JDBC."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.granule import Interval, granule, interval_from_qualifiers

QUADS = "s string, p string, o string, start string, end string"
STATEMENTS = "s string, p string, o string, qualifiers map<string,string>, _corrupt string"


def _facts(df: DataFrame, time: Interval, kind, src: str) -> DataFrame:
    fid = F.md5(F.concat_ws("\u0001", "s", "p", "o", *[F.coalesce(c.cast("string"), F.lit("-")) for c in (time.start.lo, time.start.hi, time.end.lo, time.end.hi)]))
    timed = time.start.lo.isNotNull() | time.end.lo.isNotNull()
    return df.where("s is not null and p is not null and o is not null").select(fid.alias("fact_id"), "s", "p", "o", kind.alias("o_kind"), *time.named(), timed.alias("is_temporal"), F.lit(src).alias("src"))


def read_quads(spark: SparkSession, path: str, sep: str = "\t", literals: tuple[str, ...] = ()) -> DataFrame:
    """Rows s, p, o, start, end with labels such as 2003-07; empty labels are absent. `literals` names properties whose objects are literals."""
    df = spark.read.schema(QUADS).option("sep", sep).option("mode", "PERMISSIVE").csv(path)
    kind = F.when(F.col("p").isin(*literals), "lit").otherwise("res") if literals else F.lit("res")
    return _facts(df, Interval(granule(F.col("start")), granule(F.col("end"))), kind, "quads")


def read_statements(spark: SparkSession, path: str) -> DataFrame:
    """JSON lines of statements whose qualifiers give a point in time, a start or an end; broken lines are left out."""
    df = spark.read.schema(STATEMENTS).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt").json(path)
    return _facts(df.where("_corrupt is null"), interval_from_qualifiers(F.col("qualifiers")), F.lit("res"), "statements")


def read_ranked_lists(spark: SparkSession, path: str, sep: str = "\t") -> DataFrame:
    """Rows qid, cand, score of another system's predictions; a score that is no number is absent and ranks last."""
    return spark.read.schema("qid string, cand string, score double").option("sep", sep).option("mode", "PERMISSIVE").csv(path)


def broken_statements(spark: SparkSession, path: str) -> DataFrame:
    """The lines that read_statements leaves out, as they are."""
    df = spark.read.schema(STATEMENTS).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt").json(path)
    return df.select("*").where("_corrupt is not null").select(F.col("_corrupt").alias("line"))


_TRIPLE = r'^\s*(<[^>]*>|_:\S+)\s+<([^>]*)>\s+(<[^>]*>|_:\S+|"(?:[^"\\]|\\.)*"\S*)\s*\.\s*$'


def broken_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """Lines that are no comment, not blank and no triple."""
    return spark.read.text(path).where(~F.col("value").rlike(r"^\s*(#|$)") & ~F.col("value").rlike(_TRIPLE)).select(F.col("value").alias("line"))


def read_ntriples(spark: SparkSession, path: str, start: str = "start_time", end: str = "end_time", point: str = "point_in_time") -> DataFrame:
    """N-Triples lines; a blank node with an object (`value`) and time properties is one complex fact."""
    line = spark.read.text(path).where(~F.col("value").rlike(r"^\s*(#|$)"))
    pattern = _TRIPLE
    bare = lambda c: F.regexp_replace(c, r'^<|>$|^"|"(\^\^\S+|@\S+)?$', "")
    part = lambda i: F.regexp_extract("value", pattern, i)
    t = line.select(part(1).alias("s0"), F.regexp_extract(part(2), r"([^/#]*)$", 1).alias("p"), part(3).alias("o0")).where("s0 <> ''")
    names = (start, end, point, "value")
    inner = t.where(F.col("s0").startswith("_:") & F.col("p").isin(*names)).groupBy(F.col("s0").alias("node")).agg(*[F.min(F.when(F.col("p") == n, F.col("o0"))).alias(f"q_{k}") for n, k in zip(names, ("start", "end", "point", "value"))])
    outer = t.where(~F.col("s0").startswith("_:"))
    joined = outer.join(inner, outer.o0 == inner.node, "left")
    object_ = F.coalesce("q_value", "o0")
    q = lambda k: granule(bare(F.col(f"q_{k}")))
    from ..functions.granule import Granule

    both = lambda a, b: Granule(F.coalesce(a.lo, b.lo), F.coalesce(a.hi, b.hi), F.coalesce(a.gran, b.gran))
    time = Interval(both(q("start"), q("point")), both(q("end"), q("point")))
    kind = F.when(object_.startswith('"'), "lit").otherwise("res")
    return _facts(joined.withColumns({"s": bare(F.col("s0")), "o": bare(object_), "lit_kind": kind}), time, F.col("lit_kind"), "ntriples")


def read_jdbc(spark: SparkSession, url: str, query: str, key: str, lower: int, upper: int, parts: int) -> DataFrame:
    """Quads from a database, read in parallel by ranges of a key."""
    df = spark.read.format("jdbc").options(url=url, dbtable=f"({query}) q", partitionColumn=key, lowerBound=lower, upperBound=upper, numPartitions=parts).load()
    return _facts(df, Interval(granule(F.col("start")), granule(F.col("end"))), F.lit("res"), "jdbc")


def register_quads_source(spark: SparkSession) -> None:
    """spark.read.format('quads'): local line files through the Python data source interface, for small inputs."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Quads(DataSource):
        @classmethod
        def name(cls) -> str:
            return "quads"

        def schema(self) -> str:
            return QUADS

        def reader(self, schema):
            return Reader(self.options)

    class Reader(DataSourceReader):
        def __init__(self, options) -> None:
            self.paths, self.sep = options["path"].split(","), options.get("sep", "\t")

        def partitions(self):
            return [InputPartition(p) for p in self.paths]

        def read(self, partition):
            with open(partition.value, encoding="utf-8") as f:
                for line in f:
                    row = line.rstrip("\n").split(self.sep)
                    yield tuple((row + [None] * 5)[:5])

    spark.dataSource.register(Quads)


def write_facts(facts: DataFrame, path: str, partition_by_property: bool = True) -> None:
    """Parquet with a folder per property, sorted for row-group skipping."""
    rows = facts.sortWithinPartitions("p", "s", "ts_lo")
    (rows.write.partitionBy("p") if partition_by_property else rows.write).mode("overwrite").parquet(path)


def write_bucketed(edges: DataFrame, table: str, buckets: int) -> None:
    """A table bucketed by subject: joins and aggregations by subject then need no exchange."""
    edges.write.bucketBy(buckets, "x").sortBy("x").mode("overwrite").saveAsTable(table)
