"""Benchmark decontamination: rare seeds join texts to test items, local alignment scores them.

Test items are cut into passages, and every word n-gram of a passage may be a seed.
Texts give the n-grams that some passage has (a bit table of bounded size lets few
others through); they are joined by hash with the seeds that are rare. Texts and
passages that share one are candidates: the words of the text around the seeds are
joined with the passage and aligned (Smith and Waterman's recurrence on words),
which tolerates replaced, added and left-out words. A text is contaminated when the
score is a large enough share of a full match.

Rare, for a passage, is an n-gram that no more texts have than RARE_TEXTS, or one in
RARE_SHARE texts, or SPREAD times as many as have the lower quartile of the passage's
n-grams. The last keeps a passage that many texts copy; n-grams above all three are
idiom, and a copy that holds no other is not found.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_pass, broadcast_if_small, materialize, release, text_key
from .textkernel import Words, mix, slices, windows, words_of

#: Words of a seed; words of a passage and those it shares with the next.
GRAM, PASSAGE, OVERLAP = 3, 200, 50
MATCH, MISMATCH, GAP = 2, -1, -1
#: Share of the score of a full match from which a document counts as contaminated, and least score.
SHARE, LEAST_SCORE = 0.3, 20
#: Texts that may have a rare n-gram: so many, one in so many, so many times those of the passage's lower quartile.
RARE_TEXTS, RARE_SHARE, SPREAD = 10_000, 10_000, 4
#: Most bits of the table that texts' n-grams are looked up in first (16 MB), and bits for each seed.
MOST_BITS, SEED_BITS = 27, 32
#: Candidates of a text that are cut out in one go; passages (of 1.6 kB at most) that are broadcast.
CUT_ROWS, BROADCAST_PASSAGES = 1000, 20_000


def passage_grams(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of a passage's word n-grams and their places; fewer words than that are one seed, which only texts of just these words have."""
    if len(words) >= GRAM:
        return windows(Words(None, None, np.zeros(len(words), np.int64), None, words), GRAM)
    return _whole(words), np.zeros(min(1, len(words)), np.int64)


def _whole(words: np.ndarray) -> np.ndarray:
    if not len(words):
        return np.zeros(0, np.uint64)
    key = np.uint64(len(words))
    for w in words:
        key = mix(np.array([key ^ w]))[0]
    return np.array([key], np.uint64)


def _lists(parts: list[np.ndarray]) -> pa.ListArray:
    ends = np.concatenate([[0], np.cumsum([len(p) for p in parts], dtype=np.int64)])
    flat = np.concatenate(parts).view(np.int64) if parts else np.zeros(0, np.int64)
    return pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(flat))


def _cut_items(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for s in slices(b.column("text")):
            w = words_of(s)
            parts, owner = [], []
            for i in range(s.n):
                own = w.hash[w.first[i] : w.first[i + 1]]
                for lo in range(0, max(1, len(own) - OVERLAP), PASSAGE - OVERLAP):
                    if len(part := own[lo : lo + PASSAGE]):
                        parts.append(part)
                        owner.append(s.first + i)
            ids = b.column("item_id").take(pa.array(owner, pa.int64()))
            yield pa.RecordBatch.from_arrays([ids, _lists(parts)], ["item_id", "words"])


def passages(benchmark: DataFrame) -> DataFrame:
    """pid, item_id, n_words, words (hashes) of the passages of all items; null and empty texts have none."""
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))
    cut = arrow_pass(items, _cut_items, "item_id long, words array<long>")
    return materialize(cut.select(F.monotonically_increasing_id().alias("pid"), "item_id", F.size("words").alias("n_words"), "words"), "passages")


def _seed_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        pid, hashes, places = [], [], []
        for p, words in zip(b.column("pid").to_pylist(), b.column("words")):
            keys, at = passage_grams(words.values.to_numpy().view(np.uint64))
            pid.append(np.full(len(keys), p))
            hashes.append(keys)
            places.append(at)
        if pid:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(hashes).view(np.int64)), pa.array(np.concatenate(pid)), pa.array(np.concatenate(places).astype(np.int32))], ["hash", "pid", "at"])


def bit_table(hashes: DataFrame) -> np.ndarray:
    """Bits of the hashes' top bits; the table grows with their number up to MOST_BITS, so the driver holds 16 MB at most."""
    n = hashes.agg(F.approx_count_distinct("hash")).first()[0]
    size = min(MOST_BITS, max(16, int(n * SEED_BITS).bit_length()))
    slot = F.shiftrightunsigned("hash", 64 - size)
    rows = hashes.groupBy(F.shiftright(slot, 6).alias("w")).agg(F.bit_or(F.expr(f"shiftleft(1L, cast(shiftrightunsigned(hash, {64 - size}) & 63 as int))")).alias("bits")).toArrow()
    table = np.zeros(1 << (size - 6), np.int64)
    table[rows.column("w").to_numpy()] = rows.column("bits").to_numpy()
    return table.view(np.uint64)


def _in_table(table: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Which keys may be among those of the table."""
    slot = keys >> np.uint64(64 - (len(table).bit_length() - 1 + 6))
    return (table[(slot >> np.uint64(6)).astype(np.int64)] >> (slot & np.uint64(63))) & np.uint64(1) > 0


def _hits(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.value
        for b in batches:
            for s in slices(b.column("text")):
                w = words_of(s)
                keys, at = windows(w, GRAM)
                found = np.flatnonzero(_in_table(table, keys))
                keys, at, doc = keys[found], at[found], w.doc[at[found]]
                tiny = np.flatnonzero((np.diff(w.first) < GRAM) & (np.diff(w.first) > 0))
                if len(tiny):
                    own = np.concatenate([_whole(w.hash[w.first[i] : w.first[i + 1]]) for i in tiny])
                    ok = _in_table(table, own)
                    keys, at, doc = np.concatenate([keys, own[ok]]), np.concatenate([at, w.first[tiny[ok]]]), np.concatenate([doc, tiny[ok]])
                if not len(keys):
                    continue
                _, one = np.unique(keys ^ mix(doc.astype(np.uint64) + np.uint64(1)), return_index=True)
                first = np.zeros(len(keys), np.int32)
                first[one] = 1
                row = pa.array(s.first + doc)
                rest = [b.column(c).take(row) for c in ("doc_id", "k1", "k2")]
                yield pa.RecordBatch.from_arrays([*rest, pa.array(keys.view(np.int64)), pa.array((at - w.first[doc]).astype(np.int32)), pa.array(first)], ["doc_id", "k1", "k2", "hash", "pos", "first"])

    return run


def _cut_texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The words of the text that each candidate wants."""
    for b in batches:
        k1, k2, wanted = b.column("k1").to_pylist(), b.column("k2").to_pylist(), b.column("wanted")
        for s in slices(b.column("text")):
            w = words_of(s)
            rows, parts = [], []
            for i in range(s.n):
                own = w.hash[w.first[i] : w.first[i + 1]]
                for c in wanted[s.first + i].as_py():
                    lo = max(0, c["lo"])
                    parts.append(own[lo : max(lo, c["hi"])])
                    rows.append((c["pid"], k1[s.first + i], k2[s.first + i], lo))
            if rows:
                yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in zip(*rows)), _lists(parts)], ["pid", "k1", "k2", "lo", "window"])


def align(passage: np.ndarray, text: np.ndarray) -> tuple[int, int, int, int]:
    """Best local alignment: score, matched words, first and last word of the text (exclusive)."""
    n, m = len(passage), len(text)
    h = np.zeros((n + 1, m + 1), np.int32)
    slope = np.arange(m + 1, dtype=np.int32) * -GAP
    for i in range(1, n + 1):
        prev = h[i - 1]
        row = h[i]
        row[1:] = prev[:-1] + np.where(text == passage[i - 1], MATCH, MISMATCH)
        np.maximum(row, prev + GAP, out=row)
        np.maximum(row, 0, out=row)
        row[0] = 0
        # gaps along the text: the best of all cells to the left, less their distance
        np.maximum(row, np.maximum.accumulate(row + slope) - slope, out=row)
    i, j = np.unravel_index(int(h.argmax()), h.shape)
    score, end, matched = int(h[i, j]), int(j), 0
    while i and j and h[i, j]:
        same = text[j - 1] == passage[i - 1]
        if h[i, j] == h[i - 1, j - 1] + (MATCH if same else MISMATCH):
            matched += bool(same)
            i, j = i - 1, j - 1
        elif h[i, j] == h[i - 1, j] + GAP:
            i -= 1
        else:
            j -= 1
    return score, matched, int(j), end


def least_score(n_words: int, share: float = SHARE) -> float:
    """Score from which a text counts as a copy of a passage of so many words."""
    return max(share * MATCH * n_words, min(LEAST_SCORE, 0.9 * MATCH * n_words))


_ALIGNED = "k1 long, k2 long, item_id long, share double, score long, matched_words long, word_from long, word_to long"


def _align(share: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = [pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64(), pa.int64(), pa.int64()]
        names = ["k1", "k2", "item_id", "share", "score", "matched_words", "word_from", "word_to"]
        for b in batches:
            rest = [b.column(c).to_pylist() for c in ("k1", "k2", "item_id", "lo")]
            rows = []
            for k1, k2, item, lo, p, t in zip(*rest, b.column("words"), b.column("window")):
                passage, text = p.values.to_numpy(), t.values.to_numpy()
                need = least_score(len(passage), share)
                # no alignment scores more than all words of the text that the passage has
                if MATCH * int(np.isin(text, passage).sum()) < need:
                    continue
                score, matched, a, z = align(passage, text)
                if score >= need:
                    rows.append((k1, k2, item, score / (MATCH * len(passage)), score, matched, lo + a, lo + z))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names)

    return run


def _keyed(docs: DataFrame) -> DataFrame:
    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("text is not null")
    return text.select("doc_id", *[k.alias(c) for c, k in zip(("k1", "k2"), text_key())], "text")


def _rare(seeds: DataFrame, found: DataFrame, n_texts: int) -> DataFrame:
    """Seeds that texts have and that are rare for their passage."""
    counts = found.groupBy("hash").agg(F.sum("first").alias("texts"))
    counted = materialize(seeds.join(counts, "hash", "left").withColumn("texts", F.coalesce("texts", F.lit(0))), "counted")
    quartile = counted.groupBy(F.col("pid").alias("q_pid")).agg(F.percentile_approx("texts", 0.25, 1000).alias("quartile"))
    bound = F.greatest(F.lit(RARE_TEXTS), F.lit(n_texts // RARE_SHARE), F.col("quartile") * SPREAD)
    return counted.join(quartile, F.col("pid") == F.col("q_pid")).where((F.col("texts") > 0) & (F.col("texts") <= bound)).select("hash", "pid", "at")


def _aligned(docs: DataFrame, benchmark: DataFrame, share: float) -> tuple[DataFrame, DataFrame]:
    """Best alignments (k1, k2, item_id, ..) of contaminated texts, and doc_id, k1, k2 of rows that share an n-gram with some passage."""
    texts = _keyed(docs)
    items = passages(benchmark)
    seeds = materialize(arrow_pass(items.select("pid", "words"), _seed_rows, "hash long, pid long, at int"), "seeds")
    shared = docs.sparkSession.sparkContext.broadcast(bit_table(seeds))
    hits = materialize(arrow_pass(texts, _hits(shared), "doc_id long, k1 long, k2 long, hash long, pos int, first int"), "hits")
    rows = materialize(hits.groupBy("doc_id", "k1", "k2").agg(F.count("*").alias("n_hits")), "rows")
    # one row stands for equal texts
    reps = rows.groupBy("k1", "k2").agg(F.min("doc_id").alias("r_doc"))
    one = hits.join(reps, ["k1", "k2"]).where(F.col("doc_id").eqNullSafe(F.col("r_doc"))).select("k1", "k2", "r_doc", "hash", "pos", "first").distinct()
    one = materialize(one, "one")
    rare = _rare(seeds, one, texts.count())
    rare = materialize(rare.join(items.select("pid", "n_words"), "pid"), "rare")
    near = one.join(broadcast_if_small(rare), "hash").withColumn("start", F.col("pos") - F.col("at"))
    # starts farther apart than a passage stand alone, so what is aligned stays a few passages long
    slack = (F.col("n_words") / 2).cast("int") + 8
    near = near.groupBy("k1", "k2", "r_doc", "pid", "n_words", F.floor(F.col("start") / F.col("n_words")).alias("bin")).agg(F.min("start").alias("a"), F.max("start").alias("z"))
    near = materialize(near.select("k1", "k2", "r_doc", "pid", (F.col("a") - slack).alias("lo"), (F.col("z") + F.col("n_words") + slack).alias("hi")), "near")
    parts = near.groupBy("k1", "k2").agg(F.ceil(F.count("*") / CUT_ROWS).alias("parts"))
    part = F.pmod(F.xxhash64("pid", "lo"), "parts").alias("part")
    lists = near.join(parts, ["k1", "k2"]).groupBy("k1", "k2", "r_doc", part).agg(F.collect_list(F.struct("pid", "lo", "hi")).alias("wanted"))
    lists = materialize(lists.select(F.col("k1").alias("w1"), F.col("k2").alias("w2"), "r_doc", "wanted"), "wanted")
    few = near.count()
    wide = texts.join(broadcast_if_small(lists, few), (texts.k1 == lists.w1) & (texts.k2 == lists.w2) & texts.doc_id.eqNullSafe(lists.r_doc))
    cut = arrow_pass(wide.select("k1", "k2", "text", "wanted"), _cut_texts, "pid long, k1 long, k2 long, lo long, window array<long>")
    body = F.broadcast(items) if items.count() <= BROADCAST_PASSAGES else items
    found = arrow_pass(cut.join(body, "pid").select("k1", "k2", "item_id", "lo", "words", "window"), _align(share), _ALIGNED)
    best = found.groupBy("k1", "k2", "item_id").agg(F.max(F.struct("share", "score", "matched_words", "word_from", "word_to")).alias("m"))
    best = materialize(best.select("k1", "k2", "item_id", "m.*"), "aligned")
    release(hits, one, near)
    return best, rows


def contaminated(docs: DataFrame, benchmark: DataFrame, share: float = SHARE) -> DataFrame:
    """doc_id, item_id, score, share, matched_words, word_from, word_to: the best alignment of each contaminated pair.

    Items of one or two words are found in texts of just these words. Null and empty
    texts match nothing. Null ids are carried like others; repeated documents or items
    report the same pair once. Whole texts are searched, however long; extra columns,
    whatever their names, are ignored; empty tables give an empty result.
    """
    best, rows = _aligned(docs, benchmark, share)
    pairs = rows.join(best, ["k1", "k2"]).groupBy("doc_id", "item_id").agg(F.max(F.struct("share", "score", "matched_words", "word_from", "word_to")).alias("m"))
    return pairs.select("doc_id", "item_id", "m.score", "m.share", "m.matched_words", "m.word_from", "m.word_to")


def clean_documents(docs: DataFrame, benchmark: DataFrame, share: float = SHARE) -> DataFrame:
    """The rows whose text no item contaminates, with all their columns; a row's text decides, not its doc_id."""
    best, _ = _aligned(docs, benchmark, share)
    dirty = materialize(best.select(F.col("k1").alias("dirty1"), F.col("k2").alias("dirty2")).distinct(), "dirty")
    k1, k2 = text_key()
    return docs.join(broadcast_if_small(dirty), (k1 == dirty.dirty1) & (k2 == dirty.dirty2), "left_anti")
