"""Removal of repeated byte strings by column-wise construction of suffix orders.

Every string of LENGTH bytes selects one of its short substrings, the one of the
least hash, as its anchor; equal strings select equal anchors at equal offsets. So
only texts that share an anchor can share a string. For each anchor that occurs
twice or more, the stretches of text around its occurrences are a small collection
of documents, aligned at the anchor. One symbol per document is inserted each round,
from the last column to the first: a stable sort by the new symbol turns the order
of the suffixes after it into the order of the suffixes from it, and common prefix
lengths follow from least values over the old order. Neighbours with a common prefix
of LENGTH or more are repeated strings. Collections stream by in the sorted, external
files of the shuffle. Equal stretches enter once: all their strings are repeated anyway.

An anchor with more than HOT different stretches is subdivided: its stretches are cut
into shorter ones of SPLIT times fewer starts, at the same columns in all, which are
collections of their own. Where the stretches differed in what lies far from the anchor,
equal short ones now enter once; stretches of a single start need no order at all.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_pass, broadcast_if_small, materialize, release, runs, text_key
from .textkernel import mix, rolling, slices, sliding_min, stretch_hashes

LENGTH, GRAM = 200, 32
#: Offsets of a string at which its anchor may begin.
REACH = LENGTH - GRAM + 1
#: Different stretches of an anchor up to which they are ordered together (about 75 MB); documents inserted at once.
HOT, COLLECTION = 100_000, 8192
#: Parts into which the columns of a hot anchor are cut (twice at most: 13 * 13 = REACH); a stretch that more than one in so many of all rows have is hot.
SPLIT, HOT_SHARE = 13, 10_000
#: Starts handled at once; positions fit the low bits of a sort key.
_STRETCH, _BITS = 1 << 22, np.uint64(23)


def anchors(buf: np.ndarray, offsets: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """Runs of string starts that select the same anchor: doc, first start, number of starts, anchor position, anchor hash.

    Positions count from the start of the buffer; strings stay inside texts.
    """
    parts = []
    reach = length - gram + 1
    for a in range(0, max(1, len(buf)), _STRETCH):
        seg = buf[a : a + _STRETCH + length - 1]
        if len(seg) < length:
            continue
        h = rolling(seg, gram)
        pos = np.arange(len(h), dtype=np.uint64)
        low = sliding_min((h >> _BITS << _BITS) | pos, reach)
        at = (low & ((np.uint64(1) << _BITS) - np.uint64(1))).astype(np.int64)
        ends = offsets[1:] - a
        # a start counts if its string ends inside its text
        edge = np.zeros(len(at) + 1, np.int32)
        lo = np.clip(offsets[:-1] - a, 0, len(at))
        hi = np.clip(ends - length + 1, lo, len(at))
        np.add.at(edge, lo, 1)
        np.add.at(edge, hi, -1)
        starts = np.flatnonzero(np.cumsum(edge[:-1]) > 0)
        if not len(starts):
            continue
        q = at[starts]
        cut = np.flatnonzero(np.concatenate([[True], (q[1:] != q[:-1]) | (np.diff(starts) > 1)]))
        first = starts[cut]
        parts.append((first + a, np.diff(np.append(cut, len(starts))), q[cut] + a, h[q[cut]]))
    if not parts:
        z = np.zeros(0, np.int64)
        return z, z, z, z, np.zeros(0, np.uint64)
    first, n, q, h = (np.concatenate(x) for x in zip(*parts))
    return np.searchsorted(offsets, first, "right") - 1, first, n, q, h


def _list(values: np.ndarray, cuts: np.ndarray, kind: pa.DataType) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), pa.array(values, kind))


def _anchor_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for s in slices(b.column("text")):
            doc, first, n, q, h = anchors(s.buf, s.offsets)
            cuts = np.searchsorted(doc, np.arange(s.n + 1))
            begin = s.offsets[doc]
            same = mix(stretch_hashes(s.buf, first, n + LENGTH - 1) ^ mix(((q - first) * 512 + n).astype(np.uint64)))
            sha = [hashlib.sha256(s.buf[s.offsets[i] : s.offsets[i + 1]]).hexdigest() for i in range(s.n)]
            rest = [b.column(c).slice(s.first, s.n) for c in ("rid", "doc_id", "k1", "k2")]
            yield pa.RecordBatch.from_arrays(
                [*rest, pa.array(np.diff(s.offsets)), pa.array(sha), _list(h.view(np.int64), cuts, pa.int64()), _list(first - begin, cuts, pa.int32()), _list(n, cuts, pa.int32()), _list(q - first, cuts, pa.int32()), _list(same.view(np.int64), cuts, pa.int64())],
                ["rid", "doc_id", "k1", "k2", "n_bytes", "sha", "hash", "first", "n", "lead", "stretch"],
            )


def _slices(body: np.ndarray, first: np.ndarray, size: np.ndarray) -> pa.Array:
    """The byte strings of these places and sizes."""
    ends = np.concatenate([[0], np.cumsum(size)])
    flat = body[np.repeat(first - ends[:-1], size) + np.arange(ends[-1])]
    return pa.Array.from_buffers(pa.binary(), len(first), [None, pa.py_buffer(ends.astype(np.int32).tobytes()), pa.py_buffer(flat.tobytes())])


def _wanted(b: pa.RecordBatch) -> Iterator[tuple[int, np.ndarray, dict[str, np.ndarray]]]:
    """Each row's rid, bytes and listed stretches."""
    for i in range(b.num_rows):
        found = b.column("found")[i].values
        yield b.column("rid")[i].as_py(), np.frombuffer(b.column("text")[i].as_buffer(), np.uint8), {f.name: found.field(k).to_numpy().astype(np.int64) for k, f in enumerate(found.type)}


def _stretches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Cut out each anchor's stretch: its starts and what their strings cover."""
    for b in batches:
        for rid, body, c in _wanted(b):
            size = c["n"] + LENGTH - 1
            for lo in range(0, len(size), 1 << 14):
                at = slice(lo, lo + (1 << 14))
                n = len(size[at])
                columns = [pa.array(c["hash"][at]), pa.repeat(pa.scalar(rid, pa.int64()), n), *(pa.array(c[k][at], pa.int32()) for k in ("first", "n", "lead", "copies")), _slices(body, c["first"][at], size[at])]
                yield pa.RecordBatch.from_arrays(columns, ["hash", "rid", "first", "n", "lead", "copies", "part"])


def _halved(width: int):
    """Cut the stretches of hot anchors at every width-th column; each part's collection has the anchor's hash mixed with its column."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for rid, body, c in _wanted(b):
                column = REACH - 1 - c["lead"]
                lo, hi = column // width, (column + c["n"] - 1) // width
                times = hi - lo + 1
                row = np.repeat(np.arange(len(times)), times)
                part = lo[row] + np.arange(len(row)) - np.repeat(np.cumsum(times) - times, times)
                begin, end = np.maximum(column[row], part * width), np.minimum((column + c["n"])[row], (part + 1) * width)
                first, n = c["first"][row] + begin - column[row], end - begin
                lead = c["lead"][row] - (begin - column[row])
                order = np.argsort(first, kind="stable")
                same = np.empty(len(row), np.uint64)
                same[order] = stretch_hashes(body, first[order], n[order] + LENGTH - 1)
                same = mix(same ^ mix((lead * 512 + n).astype(np.uint64)))
                name = mix(c["hash"][row].view(np.uint64) ^ mix((part * 512 + width).astype(np.uint64)))
                yield pa.RecordBatch.from_arrays([pa.repeat(pa.scalar(rid, pa.int64()), len(row)), pa.array(name.view(np.int64)), *(pa.array(v, pa.int32()) for v in (first, n, lead)), pa.array(same.view(np.int64))], ["rid", "hash", "first", "n", "lead", "stretch"])

    return run


def repeated_starts(group: np.ndarray, shift: np.ndarray, data: np.ndarray, offsets: np.ndarray, copies: np.ndarray, length: int = LENGTH, columns: int = LENGTH + REACH, starts: int = REACH) -> np.ndarray:
    """For documents in order of their group: which columns begin a string that another document of the group has in the same column.

    Document i has bytes data[offsets[i]:offsets[i+1]] from column shift[i] on.
    """
    n = len(group)
    size = np.diff(offsets)
    table = np.zeros((columns, n), np.uint16)
    for lo in range(0, n, 4096):
        hi = min(n, lo + 4096)
        part, own = data[offsets[lo] : offsets[hi]], size[lo:hi]
        doc = np.repeat(np.arange(lo, hi), own)
        table[np.arange(len(part)) - np.repeat(offsets[lo:hi] - offsets[lo] - shift[lo:hi], own), doc] = part.astype(np.uint16) + 1
    place = np.cumsum(np.concatenate([[0], group[1:] != group[:-1]])) * 512
    inside = np.concatenate([[False], place[1:] == place[:-1]])
    order = np.arange(n)
    common = np.zeros(n + 1, np.int32)
    found = np.zeros((starts, n), bool)
    for c in range(columns - 1, -1, -1):
        symbol = table[c, order]
        by = np.argsort(place + symbol, kind="stable")
        symbol = symbol[by]
        meet = inside.copy()
        meet[1:] &= (symbol[1:] == symbol[:-1]) & (symbol[1:] > 0)
        at = np.flatnonzero(meet)
        new = np.zeros(n + 1, np.int32)
        if len(at):
            a, b = by[at - 1], by[at]
            least = common[b]
            far = np.flatnonzero(b - a > 1)
            if len(far):
                bounds = np.stack([a[far] + 1, b[far] + 1], 1).ravel()
                least[far] = np.minimum.reduceat(common, bounds)[::2]
            new[at] = np.minimum(least + 1, length)
        order, common = order[by], new
        if c < starts:
            long = common >= length
            found[c, order] = long[:-1] | long[1:]
    return found.T | ((copies > 1)[:, None] & (table[:starts] > 0).T)


def _order(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Repeated starts of the stretches of each anchor, as runs (rid, first start, last start)."""
    for t in runs(batches, ["hash"], 20_000):
        cols = {c: t.column(c).to_numpy() for c in ("hash", "rid", "first", "n", "lead", "copies")}
        parts = t.column("part").combine_chunks()
        parts = parts.chunk(0) if isinstance(parts, pa.ChunkedArray) else parts
        parts = parts.cast(pa.large_binary())
        _, offs, raw = parts.buffers()
        offsets = np.frombuffer(offs, np.int64, len(parts) + 1, parts.offset * 8)
        data = np.frombuffer(raw, np.uint8)[offsets[0] : offsets[-1]]
        offsets = offsets - offsets[0]
        group = cols["hash"]
        n, shift = cols["n"].astype(np.int64), REACH - 1 - cols["lead"].astype(np.int64)
        marks = np.zeros((len(group), REACH), bool)
        column = np.arange(REACH)[None, :]
        valid = (column >= shift[:, None]) & (column < (shift + n)[:, None])
        lo = 0
        while lo < len(group):
            hi = min(len(group), lo + COLLECTION)
            while hi < len(group) and group[hi] == group[hi - 1]:
                hi += 1
            own = offsets[lo : hi + 1] - offsets[lo]
            marks[lo:hi] = repeated_starts(group[lo:hi], shift[lo:hi], data[offsets[lo] : offsets[hi]], own, cols["copies"][lo:hi]) & valid[lo:hi]
            lo = hi
        edge = np.zeros((len(group), REACH + 2), np.int8)
        edge[:, 1:-1] = marks
        step = np.diff(edge, axis=1)
        row, begin = np.nonzero(step == 1)
        _, end = np.nonzero(step == -1)
        base = cols["first"][row] - shift[row]
        yield pa.RecordBatch.from_arrays([pa.array(cols["rid"][row]), pa.array((base + begin).astype(np.int32)), pa.array((base + end - 1).astype(np.int32))], ["rid", "lo", "hi"])


def merged(spans: list[tuple[int, int]], length: int = LENGTH) -> list[tuple[int, int]]:
    """Byte ranges that runs of string starts cover, joined where they touch."""
    out: list[list[int]] = []
    for lo, hi in sorted(spans):
        if out and lo <= out[-1][1]:
            out[-1][1] = max(out[-1][1], hi + length)
        else:
            out.append([lo, hi + length])
    return [(a, b) for a, b in out]


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = []
        for i in range(b.num_rows):
            body = memoryview(b.column("text")[i].as_buffer())
            gone = merged([(r["lo"], r["hi"]) for r in b.column("runs")[i].as_py()])
            sha, at = hashlib.sha256(), 0
            for lo, hi in gone:
                sha.update(body[at:lo])
                at = hi
            sha.update(body[at:])
            rows.append((b.column("rid")[i].as_py(), sum(hi - lo for lo, hi in gone), len(gone), sha.hexdigest()))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows)], ["rid", "n_removed", "n_spans", "kept_sha256"])


def _collections(placed: DataFrame, width: int, with_text: Callable[[DataFrame], DataFrame]) -> tuple[list[DataFrame], DataFrame]:
    """Runs (rid, lo, hi) of repeated starts in the collections of all anchors but the hot ones, and the hashes of these."""
    # equal stretches: all starts of the repeated ones are repeated, and one stands for all
    kinds = placed.groupBy("hash", "stretch").agg(F.count("*").alias("copies"), F.min(F.struct("rid", "first", "n", "lead")).alias("one"))
    kinds = materialize(kinds.select("hash", "stretch", "copies", "one.*"), "kinds")
    sizes = kinds.groupBy("hash").agg(F.count("*").alias("k"), F.min("copies").alias("least"))
    hot = materialize(sizes.where(F.col("k") > HOT).select("hash"), "hot") if width > 1 else sizes.where("false").select("hash")
    cool = kinds.join(broadcast_if_small(hot), "hash", "left_anti")
    several = materialize(cool.where("copies > 1").select("hash", "stretch", "copies"), "several")
    # at most HOT_SHARE stretches have more than that share of all rows: these don't shuffle
    many = max(1000, (several.agg(F.sum("copies")).first()[0] or 0) // HOT_SHARE)
    run = lambda rows: rows.select("rid", F.col("first").alias("lo"), (F.col("first") + F.col("n") - 1).alias("hi"))
    key = ["hash", "stretch"]
    often, seldom = (several.where(c).select(*key) for c in (F.col("copies") > many, F.col("copies") <= many))
    marked = [run(placed.join(F.broadcast(often), key))]
    marked.append(run(placed.join(F.broadcast(often), key, "left_anti").join(seldom, key)))
    if width > 1:
        # where stretches differ, those that stand alone may still share some strings
        open_ = sizes.where(f"k > 1 and least = 1 and k <= {HOT}").select("hash")
        part = materialize(kinds.join(open_, "hash"), "open")
        stretches = arrow_pass(with_text(part), _stretches, "hash long, rid long, first int, n int, lead int, copies int, part binary")
        marked.append(arrow_pass(stretches.repartition("hash").sortWithinPartitions("hash"), _order, "rid long, lo int, hi int"))
    out = materialize(reduce(DataFrame.union, marked), "marked")
    release(kinds, several, *([part] if width > 1 else []))
    return [out], hot


def remove_repeats(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every row.

    A byte goes if some string of 200 bytes over it also starts elsewhere, in the same
    text or another; all strings are judged on the input. Null text counts as empty;
    texts of fewer than 200 bytes stay whole; texts are read whole, however long;
    repeated rows repeat each other. Extra columns, whatever their names, are ignored;
    an empty table gives an empty result.
    """
    body = F.coalesce(F.col("text").cast("string"), F.lit(""))
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), body.alias("text"))
    keyed = plain.select("doc_id", *[k.alias(c) for c, k in zip(("k1", "k2"), text_key())], "text")
    fields = "rid long, doc_id long, k1 long, k2 long, n_bytes long, sha string, hash array<long>, first array<int>, n array<int>, lead array<int>, stretch array<long>"
    table = materialize(arrow_pass(keyed.select(F.monotonically_increasing_id().alias("rid"), "*"), _anchor_rows, fields), "anchors")
    slim = table.select("rid", "doc_id", "k1", "k2", "n_bytes", "sha")
    texts = materialize(slim.groupBy("k1", "k2").agg(F.min("rid").alias("rid"), F.count("*").alias("copies")), "texts")
    reps = table.join(texts.select("rid", "copies"), "rid")
    each = F.inline(F.arrays_zip("hash", "first", "n", "lead", "stretch"))
    placed = materialize(reps.select("rid", each), "placed")

    def with_text(part: DataFrame) -> DataFrame:
        listed = F.struct("hash", "first", "n", "lead", F.col("copies").cast("int").alias("copies"))
        lists = part.groupBy("rid").agg(F.collect_list(listed).alias("found"))
        named = lists.join(slim.select("rid", "doc_id", "k1", "k2"), "rid").withColumnRenamed("doc_id", "n_doc")
        one = keyed.join(named.hint("shuffle_hash"), ["k1", "k2"]).where(F.col("doc_id").eqNullSafe(F.col("n_doc")))
        return one.select("rid", F.encode("text", "UTF-8").alias("text"), "found")

    marked, width = [], REACH
    while True:
        done, hot = _collections(placed, width, with_text)
        marked += done
        if width == 1 or hot.isEmpty():
            break
        width = max(1, -(-width // SPLIT))
        # all stretches of a hot anchor are cut, equal ones too
        again = placed.join(broadcast_if_small(hot), "hash").withColumn("copies", F.lit(1))
        again = arrow_pass(with_text(again), _halved(width), "rid long, hash long, first int, n int, lead int, stretch long")
        was, placed = placed, materialize(again, "cut")
        release(was)
    release(placed)
    marked = reduce(DataFrame.union, marked)
    lists = marked.join(texts.where("copies = 1").select("rid"), "rid").groupBy("rid").agg(F.collect_list(F.struct("lo", "hi")).alias("runs"))
    named = lists.join(slim.select("rid", "k1", "k2"), "rid")
    cut = keyed.join(named.hint("shuffle_hash"), ["k1", "k2"]).select("rid", F.encode("text", "UTF-8").alias("text"), "runs")
    cut = arrow_pass(cut, _cut, "rid long, n_removed long, n_spans long, kept_sha256 string")
    per_text = texts.join(cut, "rid", "left").drop("rid")
    whole = (F.col("copies") > 1) & (F.col("n_bytes") >= LENGTH)
    empty = hashlib.sha256(b"").hexdigest()
    return slim.join(per_text, ["k1", "k2"]).select(
        "doc_id", "n_bytes",
        F.when(whole, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0))).cast("long").alias("n_removed"),
        F.when(whole, 1).otherwise(F.coalesce("n_spans", F.lit(0))).cast("long").alias("n_spans"),
        F.when(whole, empty).otherwise(F.coalesce("kept_sha256", "sha")).alias("kept_sha256"),
    )
