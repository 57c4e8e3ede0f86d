"""Sharding by sampled splitters: range partitions of nearly equal bytes.

A size-weighted sample of sort keys gives quantile boundaries; exact sizes of the
ranges between them are counted, ranges that hold too much are subdivided until none
does, and whole ranges go to shards in key order by their exact cumulative size.
"""

from __future__ import annotations

from bisect import bisect_right
from itertools import count as count_from

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, release

#: Fine ranges for each shard, sampled keys for each range.
RANGES_PER_SHARD, SAMPLES_PER_RANGE = 64, 24


def _find(keys: list[str], sk: Column) -> Column:
    """How many boundaries are at or below the key: a binary search in a constant array."""
    if not keys:
        return F.lit(0)
    table = F.split(F.lit(",".join(keys)), ",")
    steps = F.sequence(F.lit(1), F.lit(len(keys).bit_length()))
    start = F.struct(F.lit(0).alias("lo"), F.lit(len(keys)).alias("hi"))

    def step(a: Column, _: Column) -> Column:
        mid = F.shiftright(a["lo"] + a["hi"], 1)
        below = table[F.least(mid, F.lit(len(keys) - 1))] <= sk
        done = a["lo"] >= a["hi"]
        return F.struct(
            F.when(~done & below, mid + 1).otherwise(a["lo"]).alias("lo"),
            F.when(~done & ~below, mid).otherwise(a["hi"]).alias("hi"),
        )

    return F.aggregate(steps, start, step)["lo"]


def _lookup(values: list[int], at: Column) -> Column:
    return F.split(F.lit(",".join(map(str, values)) or "0"), ",")[at].cast("long")


def sort_key(key: Column, *ties: Column) -> Column:
    """A string whose order is the unsigned order of these integers, one after another."""
    return F.concat(*[F.lpad(F.hex(F.coalesce(c, F.lit(0).cast("long"))), 16, "0") for c in (key, *ties)])


def _weights(total: float, rows: int) -> Column:
    """Share of a row: of the bytes, and a part for being a row, so that many tiny rows are seen."""
    return F.col("size") / F.lit(max(float(total), 1.0)) * 0.8 + F.lit(0.2 / max(rows, 1))


def _sample(df: DataFrame, share: Column, n: int, seed: int) -> list[str]:
    """Keys drawn by weight; their expected number is n, whatever the size of the data."""
    u = F.pmod(F.xxhash64("sk", F.lit(seed)), F.lit(1 << 40)) / F.lit(float(1 << 40))
    return sorted(r[0] for r in df.where(u < share * n).select("sk").toLocalIterator())


def _quantiles(keys: list[str], parts: int) -> list[str]:
    return sorted({keys[len(keys) * i // parts] for i in range(1, parts)}) if keys else []


def assign_shards(rows: DataFrame, n_shards: int, key: str = "key", tie: str = "tie") -> DataFrame:
    """Add shard (0..n-1) and slot (gapless from 0 in each shard) to rows.

    Other columns are carried. `rows` has a long `key` (rows of a key stay together unless their range is
    overfull), a long `tie` and a long `size`; null key or tie counts as 0. Fully
    repeated rows are told apart by a number fixed when the input is first read.
    An empty input gives an empty result.
    """
    if n_shards < 1:
        raise ValueError("n_shards must be at least 1")
    salt = F.monotonically_increasing_id()
    base = materialize(rows.withColumn("sk", sort_key(F.col(key), F.col(tie), salt)), "keys")
    total, count = base.agg(F.sum("size"), F.count("*")).first()
    total, count = total or 0, count or 0
    parts = n_shards * RANGES_PER_SHARD
    bounds = _quantiles(_sample(base, _weights(total, count), parts * SAMPLES_PER_RANGE, 1), parts)
    # a boundary in mid-key moves to the key's start: rows of a key stay together
    bounds = sorted({b[:16] for b in bounds})
    most_bytes, most_rows = 2 * total / parts, max(2 * count / parts, 1)
    for turn in count_from(0):
        ranged = base.withColumn("r", _find(bounds, F.col("sk")))
        sums, over = {}, {}
        for x in ranged.groupBy("r").agg(F.sum("size").alias("b"), F.max("size").alias("m"), F.count("*").alias("n")).toLocalIterator():
            sums[x["r"]] = x["b"], x["n"]
            # a row can't be divided: what lies beside the largest one counts
            if x["n"] > 1 and (x["b"] - x["m"] > most_bytes or x["n"] > most_rows):
                over[x["r"]] = max(x["b"] / max(most_bytes, 1), x["n"] / most_rows)
        if not over:
            break
        keys = sorted(over)
        heavy = ranged.where(F.col("r").isin(keys))
        drawn = _sample(heavy, _weights(total, count), parts * SAMPLES_PER_RANGE * (turn + 2), 2 + turn)
        new: set[str] = set()
        for r in keys:
            lo, hi = bounds[r - 1] if r else "", bounds[r] if r < len(bounds) else None
            own = drawn[bisect_right(drawn, lo) : bisect_right(drawn, hi) if hi else None]
            new |= set(_quantiles(own, int(2 * over[r]) + 2))
        # keys are unique and draws grow, so an overfull range gets a boundary sooner or later
        bounds = sorted({*bounds, *new})
    shard, offset, at, filled = [], [], 0, [0] * n_shards
    for r in range(len(bounds) + 1):
        b, n = sums.get(r, (0, 0))
        k = min(n_shards - 1, int((at + b / 2) * n_shards / total)) if total else 0
        shard.append(k)
        offset.append(filled[k])
        filled[k] += n
        at += b
    within = Window.partitionBy("r").orderBy("sk")
    placed = ranged.withColumn("shard", _lookup(shard, F.col("r")).cast("int")).withColumn(
        "slot", _lookup(offset, F.col("r")) + F.row_number().over(within) - 1
    )
    return placed.drop("r", "sk")


def shard_documents(docs: DataFrame, n_shards: int = 16) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every document.

    Size is the text's UTF-8 bytes plus 1 (null text: 1; its CRC is that of no
    bytes). Equal texts lie side by side in key order. Extra columns are ignored.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    slim = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(F.encode(text, "UTF-8")).cast("long").alias("text_crc32"),
        F.xxhash64(text).alias("key"),
        F.xxhash64("doc_id").alias("tie"),
    )
    out = assign_shards(slim, n_shards)
    return out.select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard")
    )
