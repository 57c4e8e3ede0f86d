"""Quality classifier: interpolated modified Kneser-Ney over characters of trusted text.

A 5-gram of code points fits two longs (21 bits each), so contexts and suffixes are
bit operations. Texts are dealt to blocks. One pass counts the 5-grams of each block,
those of trusted training texts apart. Count tables of all orders are joined, in
shards by key, with the 5-grams that the corpus has, which gives each its
interpolated probability; a join by 5-gram sends it to the blocks that have it.
Texts (packed) and scored 5-grams of a block meet in one task, which sums the
log-probabilities of every document. Trusted texts that were held out give each
language its quantile of perplexity, above which documents are rejected. Nothing
that grows with the corpus goes through the driver.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow_pass, broadcast_if_small, materialize, release, text_key
from .textkernel import Slice, mix, slices

ORDER, BITS = 5, 21
ONE, TWO = (1 << BITS) - 1, (1 << 2 * BITS) - 1
#: One trusted text in FOLDS is held out; the quantile of their perplexity; least number of held-out texts of a language.
FOLDS, QUANTILE, LEAST_HELD = 5, 0.995, 20
#: Rows that follow each other in a file and share a block; bytes of text of a block; bytes of text packed together.
CHUNK_ROWS, BLOCK_BYTES, PACK_BYTES = 16_384, 192 << 20, 4 << 20
#: Different 5-grams of a block and language that a task holds before it passes them on.
HELD_GRAMS = 500_000
#: Bytes of text whose 5-grams are formed at once: each byte takes about 100 bytes of arrays.
SLICE = 1 << 18
#: Trusted document numbers are broadcast up to this many (8 bytes each), else joined by shuffle.
BROADCAST_IDS = 2_000_000

_KEY = ["lang", "hi", "lo"]


def symbols(s: Slice) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """5-grams (two code points, three code points) that end at each code point of a slice, and the first of each text (one more at the end); texts begin with line feeds."""
    lead = (s.buf & 0xC0) != 0x80
    count = np.concatenate([[0], np.cumsum(lead)])[s.offsets]
    points = np.frombuffer(s.buf.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32).astype(np.uint64)
    pad = ORDER - 1
    full = np.full(len(points) + pad * s.n, 10, np.uint64)
    end = np.arange(len(points)) + pad * (np.repeat(np.arange(s.n), np.diff(count)) + 1)
    full[end] = points
    one, two = np.uint64(BITS), np.uint64(2 * BITS)
    return full[end - 4] << one | full[end - 3], full[end - 2] << two | full[end - 1] << one | points, count


def gram_keys(hi: np.ndarray, lo: np.ndarray, lang: str | None) -> np.ndarray:
    """64-bit hashes of 5-grams of a language."""
    own = np.uint64(int.from_bytes(hashlib.blake2b((lang or "").encode(), digest_size=8).digest(), "little"))
    return mix(lo ^ mix(hi + own))


def _runs(hi: np.ndarray, lo: np.ndarray, n: np.ndarray | None = None, train: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """Different 5-grams and their summed counts; without counts, each stands for one."""
    key = gram_keys(hi, lo, None)
    order = np.argsort(key)
    key = key[order]
    cut = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    at = order[cut]
    if n is None:
        return hi[at], lo[at], np.diff(np.append(cut, len(key)))
    return hi[at], lo[at], np.add.reduceat(n[order], cut), np.add.reduceat(train[order], cut)


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """5-grams of each block and language, counted: all, and those of training texts."""
    held: dict[tuple[int, str], list] = {}

    def merge(key: tuple[int, str]) -> None:
        held[key] = [_runs(*(np.concatenate(x) for x in zip(*held[key])))]

    def flush(key: tuple[int, str]) -> pa.RecordBatch:
        merge(key)
        (hi, lo, n, train), = held.pop(key)
        block, lang = pa.repeat(pa.scalar(key[0], pa.int64()), len(hi)), pa.repeat(pa.scalar(key[1], pa.string()), len(hi))
        return pa.RecordBatch.from_arrays([block, lang, pa.array(hi.view(np.int64)), pa.array(lo.view(np.int64)), pa.array(n), pa.array(train)], ["block", *_KEY, "n", "n_train"])

    for b in batches:
        langs, roles, blocks = np.array([x or "" for x in b.column("lang").to_pylist()], object), b.column("role").to_numpy(), b.column("block").to_numpy()
        for s in slices(b.column("text"), SLICE):
            hi, lo, first = symbols(s)
            own, size = np.arange(s.first, s.last), np.diff(first)
            for key in sorted(set(zip(blocks[own].tolist(), langs[own]))):
                for train in (False, True):
                    pick = (blocks[own] == key[0]) & (langs[own] == key[1]) & ((roles[own] == 1) == train)
                    if not (many := int(size[pick].sum())):
                        continue
                    if many < len(hi):
                        wide = np.repeat(pick, size)
                        h, l, n = _runs(hi[wide], lo[wide])
                    else:
                        h, l, n = _runs(hi, lo)
                    held.setdefault(key, []).append((h, l, n, n if train else np.zeros(len(n), np.int64)))
                if len(held.get(key, ())) > 24:
                    merge(key)
                    if len(held[key][0][0]) > HELD_GRAMS:
                        yield flush(key)
        # rows of a block follow each other: others are done, for now
        for key in [k for k in held if k[0] not in blocks]:
            yield flush(key)
    for key in sorted(held):
        yield flush(key)


def _suffix(n: int) -> list[Column]:
    """The last n code points of a 5-gram."""
    hi = {5: F.col("hi"), 4: F.col("hi").bitwiseAND(F.lit(ONE))}.get(n, F.lit(0).cast("long"))
    lo = {1: F.col("lo").bitwiseAND(F.lit(ONE)), 2: F.col("lo").bitwiseAND(F.lit(TWO))}.get(n, F.col("lo"))
    return [hi.alias("hi"), lo.alias("lo")]


def _context() -> list[Column]:
    """All but the last code point of an n-gram."""
    lo = F.shiftrightunsigned("lo", BITS).bitwiseOR(F.shiftleft(F.col("hi").bitwiseAND(F.lit(ONE)), 2 * BITS))
    return [F.shiftrightunsigned("hi", BITS).alias("chi"), lo.alias("clo")]


def _discounts(table: DataFrame) -> DataFrame:
    """Per language the three discounts of an order, from how many n-grams have counts 1 to 4."""
    n = {k: F.sum((F.col("c") == k).cast("double")) for k in (1, 2, 3, 4)}
    raw = table.groupBy("lang").agg(*[n[k].alias(f"n{k}") for k in n])
    y = F.col("n1") / (F.col("n1") + 2 * F.col("n2"))

    def d(k: int, default: float) -> Column:
        value = k - (k + 1) * y * F.col(f"n{k + 1}") / F.col(f"n{k}")
        ok = (F.col("n1") > 0) & (F.col("n2") > 0) & (F.col(f"n{k}") > 0) & (F.col(f"n{k + 1}") > 0)
        return F.when(ok, F.greatest(F.least(value, F.lit(k - 0.05)), F.lit(0.05))).otherwise(F.lit(default)).alias(f"d{k}")

    return raw.select("lang", d(1, 0.5), d(2, 1.0), d(3, 1.5))


def probabilities(grams: DataFrame) -> DataFrame:
    """Of rows (lang, hi, lo, n_train): lang, hi, lo, logp of each 5-gram; null logp where the language has no training text."""
    counts = {ORDER: materialize(grams.where("n_train > 0").select(*_KEY, F.col("n_train").alias("c")), "c5")}
    for n in range(ORDER - 1, 0, -1):
        # lower orders count in how many contexts an n-gram continues
        counts[n] = materialize(counts[n + 1].select("lang", *_suffix(n)).groupBy(*_KEY).agg(F.count("*").alias("c")), f"c{n}")
    vocabulary = broadcast_if_small(materialize(counts[1].groupBy("lang").agg((F.count("*") + 1).alias("v")), "v"))
    below = now = None
    for n in range(1, ORDER + 1):
        discount = broadcast_if_small(materialize(_discounts(counts[n]), f"d{n}"))
        drop = F.when(F.col("c") == 1, F.col("d1")).when(F.col("c") == 2, F.col("d2")).otherwise(F.col("d3"))
        table = counts[n].join(discount, "lang").withColumn("drop", drop)
        context = table.select("lang", *_context(), "c", "drop").groupBy("lang", "chi", "clo").agg(F.sum("c").alias("total"), F.sum("drop").alias("freed"))
        kept = table.select(*_KEY, F.greatest(F.col("c") - F.col("drop"), F.lit(0.0)).alias("left"))
        wanted = grams.select("lang", *_suffix(n)).distinct()
        rows = wanted.select("*", *_context()).join(kept, _KEY, "left").join(context, ["lang", "chi", "clo"], "left")
        if below is None:
            rows = rows.join(vocabulary, "lang", "left").withColumn("lower", 1.0 / F.col("v"))
        else:
            low = _suffix(n - 1)
            rows = rows.withColumns({"bhi": low[0], "blo": low[1]}).join(below, ["lang", "bhi", "blo"])
        p = F.when(F.col("total").isNull(), F.col("lower")).otherwise((F.coalesce("left", F.lit(0.0)) + F.col("freed") * F.col("lower")) / F.col("total"))
        was, now = now, materialize(rows.select(*_KEY, p.alias("p")), f"p{n}")
        if was is not None:
            release(was)
        below = now.select("lang", F.col("hi").alias("bhi"), F.col("lo").alias("blo"), F.col("p").alias("lower"))
    release(*counts.values())
    return now.select(*_KEY, F.log("p").cast("float").alias("logp"))


class Table:
    """An open-addressing table from 64-bit keys to floats."""

    def __init__(self, keys: np.ndarray, values: np.ndarray) -> None:
        bits = max(4, int(np.ceil(np.log2(max(2, 2 * len(keys))))))
        self.shift, self.mask = np.uint64(64 - bits), (1 << bits) - 1
        self.keys, self.values = np.zeros(1 << bits, np.uint64), np.full(1 << bits, np.nan, np.float32)
        self.used = np.zeros(1 << bits, bool)
        todo = np.arange(len(keys))
        slot = (keys >> self.shift).astype(np.int64)
        while len(todo):
            free = ~self.used[slot]
            place, one = np.unique(slot[free], return_index=True)
            won = np.flatnonzero(free)[one]
            self.used[place] = True
            self.keys[place], self.values[place] = keys[todo[won]], values[todo[won]]
            rest = np.ones(len(todo), bool)
            rest[won] = False
            todo, slot = todo[rest], (slot[rest] + 1) & self.mask

    def get(self, keys: np.ndarray) -> np.ndarray:
        """Values of keys; nan for a key that isn't there."""
        slot = (keys >> self.shift).astype(np.int64)
        hit = self.keys[slot] == keys
        out = np.where(hit, self.values[slot], np.float32(np.nan))
        todo = np.flatnonzero(~hit & self.used[slot])
        slot = slot[todo]
        while len(todo):
            slot = (slot + 1) & self.mask
            hit = self.keys[slot] == keys[todo]
            out[todo[hit]] = self.values[slot[hit]]
            more = ~hit & self.used[slot]
            todo, slot = todo[more], slot[more]
        return out


_TEXTS = pa.schema([("doc_id", pa.int64()), ("lang", pa.string()), ("role", pa.int32()), ("k1", pa.int64()), ("k2", pa.int64()), ("text", pa.string())])


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts of a block compressed together, about PACK_BYTES at once."""
    held: dict[int, list] = {}
    size: dict[int, int] = {}

    def flush(block: int) -> pa.RecordBatch:
        sink = pa.BufferOutputStream()
        rows = held.pop(block)
        size.pop(block)
        with pa.ipc.new_stream(sink, rows[0].schema) as out:
            for r in rows:
                out.write_batch(r)
        packed = zstandard.ZstdCompressor(level=3).compress(sink.getvalue())
        return pa.RecordBatch.from_arrays([pa.array([block], pa.int64()), pa.array([packed], pa.binary())], ["block", "packed"])

    for b in batches:
        blocks = b.column("block").to_numpy()
        rows = b.select(_TEXTS.names)
        for block in np.unique(blocks).tolist():
            held.setdefault(block, []).append(rows.filter(pa.array(blocks == block)))
            size[block] = size.get(block, 0) + held[block][-1].nbytes
            if size[block] >= PACK_BYTES:
                yield flush(block)
    for block in sorted(held):
        yield flush(block)


def _sum(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by block, scored 5-grams before texts: symbols and summed log-probability of each document."""
    now, keys, values, table = None, [], [], None
    for b in batches:
        blocks = b.column("block").to_numpy()
        cuts = [0, *(np.flatnonzero(blocks[1:] != blocks[:-1]) + 1).tolist(), len(blocks)]
        for lo, hi in zip(cuts, cuts[1:]):
            if lo == hi:
                continue
            if now != blocks[lo]:
                now, keys, values, table = blocks[lo], [], [], None
            part = b.slice(lo, hi - lo)
            n = part.num_rows - part.column("packed").null_count
            grams = part.slice(0, part.num_rows - n)
            if grams.num_rows:
                lang = grams.column("lang").dictionary_encode()
                which = lang.indices.to_numpy()
                h, l, v = (grams.column(c).to_numpy() for c in ("hi", "lo", "logp"))
                for i, name in enumerate(lang.dictionary.to_pylist()):
                    at = which == i
                    keys.append(gram_keys(h[at].view(np.uint64), l[at].view(np.uint64), name))
                    values.append(v[at])
            for packed in part.column("packed").slice(part.num_rows - n):
                if table is None:
                    table = Table(np.concatenate([np.zeros(0, np.uint64), *keys]), np.concatenate([np.zeros(0, np.float32), *values]))
                    keys, values = [], []
                raw = zstandard.ZstdDecompressor().decompress(packed.as_buffer())
                for texts in pa.ipc.open_stream(raw):
                    yield _scored(texts, table)


def _scored(b: pa.RecordBatch, table: Table) -> pa.RecordBatch:
    langs = np.array([x or "" for x in b.column("lang").to_pylist()], object)
    total, seen = [np.zeros(0)], [np.zeros(0, np.int64)]
    for s in slices(b.column("text"), SLICE):
        hi, lo, first = symbols(s)
        own, n = langs[s.first : s.last], np.diff(first)
        keys = np.empty(len(hi), np.uint64)
        for lang in set(own):
            pick = np.repeat(own == lang, n)
            keys[pick] = gram_keys(hi[pick], lo[pick], lang)
        value = table.get(keys)
        there = ~np.isnan(value)
        sums = np.concatenate([[0.0], np.cumsum(np.where(there, value, 0).astype(np.float64))])
        many = np.concatenate([[0], np.cumsum(there)])
        total.append(np.diff(sums[first]))
        seen.append(np.diff(many[first]))
    rest = [b.column(c) for c in ("doc_id", "lang", "role", "k1", "k2")]
    return pa.RecordBatch.from_arrays([*rest, pa.array(np.concatenate(seen)), pa.array(np.concatenate(total))], ["doc_id", "lang", "role", "k1", "k2", "n_symbols", "logp"])


def _summed(marked: DataFrame, requests: DataFrame, scored: DataFrame, blocks: int) -> DataFrame:
    """Symbols and summed log-probability of every document: scored 5-grams are joined with the blocks that have them, and meet the block's texts."""
    there = requests.select("block", *_KEY).join(scored.where("logp is not null"), _KEY)
    there = there.select("block", *_KEY, "logp", F.lit(None).cast("binary").alias("packed"))
    packed = arrow_pass(marked, _pack, "block long, packed binary")
    texts = packed.select("block", F.lit(None).cast("string").alias("lang"), F.lit(None).cast("long").alias("hi"), F.lit(None).cast("long").alias("lo"), F.lit(None).cast("float").alias("logp"), "packed")
    both = there.unionByName(texts).repartition(2 * blocks, "block").sortWithinPartitions("block", F.col("packed").isNotNull())
    return arrow_pass(both, _sum, "doc_id long, lang string, role int, k1 long, k2 long, n_symbols long, logp double")


def _dealt(docs: DataFrame) -> tuple[DataFrame, int]:
    """doc_id, lang, text, block, and the number of blocks: rows that follow each other in a file share a block, whatever splits a cluster reads; rows without files are written first."""
    slim = [F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text")]
    place = [F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("row")]
    try:
        rows = docs.select(*slim, *place)
    except AnalysisException:
        rows = materialize(docs.select(*slim), "texts").select(*slim, *place)
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = size // BLOCK_BYTES + 1
    block = F.pmod(F.xxhash64("file", F.floor(F.col("row") / CHUNK_ROWS)), F.lit(blocks))
    return rows.select("doc_id", "lang", "text", block.alias("block")), blocks


def classify(docs: DataFrame, labels: DataFrame, quantile: float = QUANTILE) -> DataFrame:
    """doc_id, lang, n_symbols, perplexity, threshold, kept of every document.

    Trusted are documents labelled of quality 1 and not toxic, by all their labels.
    The threshold of a language is the quantile over its held-out trusted texts; where
    fewer than LEAST_HELD are held out, over all its trusted texts. Null text counts as
    empty; a document without symbols, or of a language without trusted text, has null
    perplexity and is kept. Null language is one of its own. Texts are scored whole,
    however long. Repeated rows each get a row; extra columns, whatever their names,
    are ignored; an empty table gives an empty result.
    """
    good = (F.coalesce("quality", F.lit(0)) == 1) & (F.coalesce("toxic", F.lit(0)) == 0)
    trusted = materialize(labels.groupBy(F.col("doc_id").cast("long").alias("t_id")).agg(F.min(good.cast("int")).alias("good")).where("good = 1 and t_id is not null").select("t_id"), "trusted")
    few = trusted.count() <= BROADCAST_IDS
    k1, k2 = text_key()
    role = F.when(F.col("t_id").isNull(), 0).when(F.pmod("k1", F.lit(FOLDS)) == 0, 2).otherwise(1)
    dealt, blocks = _dealt(docs)
    marked = dealt.withColumns({"k1": k1, "k2": k2}).join(F.broadcast(trusted) if few else trusted, F.col("doc_id") == F.col("t_id"), "left").withColumn("role", role.cast("int")).drop("t_id")
    counted = arrow_pass(marked.select("block", "lang", "role", "text"), _count, "block long, lang string, hi long, lo long, n long, n_train long")
    requests = materialize(counted.groupBy("block", *_KEY).agg(F.sum("n").alias("n"), F.sum("n_train").alias("n_train")), "requests")
    grams = materialize(requests.groupBy(*_KEY).agg(F.sum("n").alias("n"), F.sum("n_train").alias("n_train")), "grams")
    scored = probabilities(grams)
    sums = materialize(_summed(marked, requests, scored, blocks), "sums").withColumn("perplexity", F.when(F.col("n_symbols") > 0, F.exp(-F.col("logp") / F.col("n_symbols"))))
    cut = lambda role: F.percentile_approx(F.when(role, F.col("perplexity")), quantile, 10_000)
    held = F.col("role") == 2
    limit = sums.where("role > 0").groupBy(F.coalesce("lang", F.lit("")).alias("l")).agg(F.when(F.count(F.when(held, 1)) >= LEAST_HELD, cut(held)).otherwise(cut(F.col("role") > 0)).alias("threshold"))
    limit = materialize(limit, "limits")
    out = sums.join(broadcast_if_small(limit), F.coalesce("lang", F.lit("")) == limit.l, "left")
    kept = F.coalesce(F.col("perplexity") <= F.col("threshold"), F.lit(True))
    release(grams, requests)
    return out.select("doc_id", "lang", "n_symbols", "perplexity", "threshold", kept.alias("kept"))
