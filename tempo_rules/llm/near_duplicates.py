"""Joining texts whose sets of word windows are alike, by an LSH forest of MinHash prefixes.

Equal texts are one class from the start. Every class has a path of MinHash values
in each tree of the forest; sorted paths are prefix tries, walked once. A text is
first compared with the texts it most often meets in the tries; links found so make
clusters, whose pairs are all compared, in blocks. What is left are pairs of different
clusters that share a prefix. Prefixes are shortened, level by level, until they have
the target recall for links as alike as those found so far; pairs that share one are
compared, which may show links that ask for shorter ones. Every pair is compared once,
where its texts first meet. Only verified links join texts, so what merely meets by
way of others is never gathered.
"""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, arrow_pass, broadcast_if_small, materialize, rebatched, release, runs, text_key
from .components import components
from .textkernel import Slice, slices, windows, words_of

WORDS, SIMILARITY = 5, Fraction(4, 5)
TREES, DEPTH, RECALL = 24, 8, 0.9999
#: Texts of a group that are compared at once, with as many others.
BLOCK = 256

_FACTORS = np.random.Generator(np.random.PCG64(7)).integers(1, 2**63, TREES * DEPTH, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def meeting(similarity, prefix: int):
    """Probability that texts of this similarity share a prefix of this length in some tree."""
    return 1 - (1 - similarity**prefix) ** TREES


def prefix_length(similarity: float = float(SIMILARITY), trees: int = TREES, depth: int = DEPTH, recall: float = RECALL) -> int:
    """The longest prefix at which texts of this similarity still meet in some tree with the target probability: no prefix needs to be shorter."""
    for r in range(depth, 0, -1):
        if 1 - (1 - similarity**r) ** trees >= recall:
            return r
    raise ValueError("too few trees for this recall")


#: Lengths of prefixes, the shortest first.
LEVELS = tuple(range(prefix_length(), DEPTH + 1))


def shingles(s: Slice, n: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all word windows of a slice, and the first window of each text (one more at the end)."""
    w = words_of(s)
    keys, at = windows(w, n)
    return keys, np.searchsorted(w.doc[at] if len(at) else np.zeros(0, np.int64), np.arange(s.n + 1))


def paths(keys: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Per text and tree, two longs that hold DEPTH MinHash values of 16 bits, the first value on top; texts without windows get zeros."""
    n = len(first) - 1
    out = np.zeros((n, TREES * DEPTH), np.uint64)
    full = np.flatnonzero(np.diff(first) > 0)
    if len(full):
        at = first[:-1][full]
        for k, a in enumerate(_FACTORS):
            out[full, k] = np.minimum.reduceat(keys * a, at)
    level = ((out * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(48)).reshape(n, TREES, 2, DEPTH // 2)
    packed = np.zeros((n, TREES, 2), np.uint64)
    for k in range(DEPTH // 2):
        packed |= level[:, :, :, k] << np.uint64(48 - 16 * k)
    return packed.reshape(n, TREES * 2).view(np.int64)


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        sizes, rows = [np.zeros(0, np.int64)], [np.zeros((0, TREES * 2), np.int64)]
        for s in slices(b.column("text"), 1 << 20):
            keys, first = shingles(s)
            sizes.append(np.diff(first))
            rows.append(paths(keys, first))
        flat = np.concatenate(rows)
        lists = pa.ListArray.from_arrays(pa.array(np.arange(len(flat) + 1, dtype=np.int32) * (TREES * 2)), pa.array(flat.ravel()))
        yield pa.RecordBatch.from_arrays(
            [*(b.column(c) for c in ("rid", "doc_id", "k1", "k2")), pa.array(np.concatenate(sizes)), lists], ["rid", "doc_id", "k1", "k2", "n_windows", "paths"]
        )


def signed(docs: DataFrame) -> DataFrame:
    """rid, doc_id, k1, k2, n_windows, paths of every row; rid is fixed by writing the table."""
    slim = docs.select(
        F.monotonically_increasing_id().alias("rid"), F.col("doc_id").cast("long").alias("doc_id"), *[k.alias(c) for c, k in zip(("k1", "k2"), text_key())], F.col("text").cast("string").alias("text")
    )
    return materialize(arrow_pass(slim, _sign, "rid long, doc_id long, k1 long, k2 long, n_windows long, paths array<long>"), "signed")


class _Walk:
    """Rows sorted by tree and path: of each text that shares the shortest prefix, per level the first text that shares the prefix (-1: none does), and the text before."""

    def __init__(self) -> None:
        self.last = None

    def rows(self, tree: np.ndarray, hi: np.ndarray, lo: np.ndarray, rid: np.ndarray, final: bool = False) -> dict[str, np.ndarray]:
        """Rows that are done; the last one waits for the next."""
        held = self.last
        if held is not None:
            tree, hi, lo, rid = (np.concatenate([[h], v]) for h, v in zip(held["row"], (tree, hi, lo, rid)))
        n = len(rid)
        if not n:
            return {}
        half = DEPTH // 2
        cut = lambda v, k: v >> np.int64(64 - 64 // half * k) if k else np.zeros_like(v)
        out, lead, before = {}, {}, {}
        for r in LEVELS:
            same = (tree[1:] == tree[:-1]) & (cut(hi[1:], min(r, half)) == cut(hi[:-1], min(r, half))) & (cut(lo[1:], max(0, r - half)) == cut(lo[:-1], max(0, r - half)))
            first = np.maximum.accumulate(np.where(np.concatenate([[True], ~same]), np.arange(n), 0))
            lead[r] = rid[first]
            before[r] = np.concatenate([[False], same])
            if held is not None:
                lead[r] = np.where(first == 0, held["lead"][r], lead[r])
                before[r][0] = held["before"][r]
            out[f"l{r}"] = np.where(before[r] | np.concatenate([same, [False]]), lead[r], -1)
        near = np.concatenate([[-1], rid[:-1]])
        near[~before[LEVELS[0]]] = -1
        if held is not None:
            near[0] = held["near"]
        done = n if final else n - 1
        self.last = {"row": (tree[-1], hi[-1], lo[-1], rid[-1]), "lead": {r: lead[r][-1] for r in LEVELS}, "before": {r: before[r][-1] for r in LEVELS}, "near": near[-1]}
        out = {"rid": rid, "tree": tree, **out, "near": near}
        pick = np.flatnonzero(out[f"l{LEVELS[0]}"][:done] >= 0)
        return {c: v[pick] for c, v in out.items()}


_PLACE = "rid long, tree int, " + ", ".join(f"l{r} long" for r in LEVELS) + ", near long"


def _walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    walk = _Walk()
    empty = [np.zeros(0, np.int64)] * 4

    def batch(rows: dict[str, np.ndarray]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(v, pa.int32() if c == "tree" else pa.int64()) for c, v in rows.items()], list(rows))

    for t in rebatched(batches):
        yield batch(walk.rows(*(t.column(c).to_numpy().astype(np.int64) for c in ("tree", "hi", "lo", "rid"))))
    if walk.last is not None:
        yield batch(walk.rows(*empty, final=True))


def places(texts: DataFrame) -> DataFrame:
    """rid, tree, l5 .. l8, near of texts that share the shortest prefix with another in a tree."""
    trees = F.transform(F.sequence(F.lit(0), F.lit(TREES - 1)), lambda i: F.struct(i.alias("tree"), F.element_at("paths", i * 2 + 1).alias("hi"), F.element_at("paths", i * 2 + 2).alias("lo")))
    rows = texts.where("n_windows > 0").select("rid", F.inline(trees))
    # a subtrie's rows meet in one sorted run, which is streamed, not held
    level = lambda c, n: F.shiftright(c, 64 - 16 * n) if n < 4 else F.col(c)
    prefix = LEVELS[0]
    key = ["tree", level("hi", min(prefix, 4))] + ([level("lo", prefix - 4)] if prefix > 4 else [])
    return arrow_pass(rows.repartition(*key).sortWithinPartitions("tree", "hi", "lo", "rid"), _walk, _PLACE)


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        out = []
        for s in slices(b.column("text")):
            keys, first = shingles(s)
            out += [np.unique(keys[first[i] : first[i + 1]]).tobytes() for i in range(s.n)]
        yield pa.RecordBatch.from_arrays([b.column("rid"), b.column("copies"), pa.array(out, pa.binary())], ["rid", "copies", "keys"])


def overlaps(sets: list[np.ndarray], others: list[np.ndarray] | None = None) -> np.ndarray:
    """Sizes of the intersections of each set with each other one."""
    both = sets + (others or [])
    if len(both) == 2 and others is None:
        n = len(np.intersect1d(both[0], both[1], assume_unique=True))
        return np.array([[len(both[0]), n], [n, len(both[1])]])
    owner = np.repeat(np.arange(len(both)), [len(x) for x in both])
    _, ids, counts = np.unique(np.concatenate(both), return_inverse=True, return_counts=True)
    shared = counts[ids] > 1
    owner, ids = owner[shared], ids[shared]
    left, right = len(sets), len(both) - len(sets)
    out = np.zeros((left, right or left))
    order = np.argsort(ids, kind="stable")
    owner, ids = owner[order], ids[order]
    _, dense = np.unique(ids, return_inverse=True)
    width = 4096
    for lo in range(0, int(dense[-1]) + 1 if len(dense) else 0, width):
        i, j = np.searchsorted(dense, [lo, lo + width])
        m = np.zeros((len(both), width), np.float32)
        m[owner[i:j], dense[i:j] - lo] = 1
        out += m[:left] @ (m[left:].T if right else m.T)
    n = np.rint(out).astype(np.int64)
    if not right:
        n[np.arange(left), np.arange(left)] = [len(x) for x in sets]
    return n


def _least_labels(linked: np.ndarray, ids: np.ndarray) -> np.ndarray:
    labels = ids.copy()
    while True:
        new = np.minimum(labels, np.where(linked, labels[None, :], np.iinfo(np.int64).max).min(1))
        if (new == labels).all():
            return labels
        labels = new


_GROUP = "g1 long, g2 long, rid long, side int, mask binary"


def _bits(mask: np.ndarray) -> list[bytes]:
    return [row.tobytes() for row in np.packbits(mask, axis=1)]


def _cuts(cols: dict[str, np.ndarray]) -> list[tuple[int, int]]:
    n = len(cols["g1"])
    at = (np.flatnonzero((cols["g1"][1:] != cols["g1"][:-1]) | (cols["g2"][1:] != cols["g2"][:-1])) + 1).tolist()
    return list(zip([0, *at], [*at, n]))


def _open_pairs(level: int, longer: int | None):
    """Of groups of texts that share a prefix of this length in a tree: pairs of different clusters that meet here first, and share no prefix of the
    longer length that was compared before, as a bit mask for each text."""
    fields_of = {"own": f"l{level}"} | ({"longer": f"l{longer}"} if longer else {})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in runs(batches, ["g1", "g2"], 4000):
            cols = {c: t.column(c).to_numpy() for c in ("g1", "g2", "rid", "side", "root", "tree")}
            marks = t.column("marks").combine_chunks()
            marks = marks.chunk(0) if isinstance(marks, pa.ChunkedArray) else marks
            fields, size = marks.flatten(), np.diff(marks.offsets.to_numpy())
            at = (np.repeat(np.arange(t.num_rows), size), fields.field("tree").to_numpy())
            lead = {}
            for k, name in fields_of.items():
                lead[k] = np.full((t.num_rows, TREES), -1, np.int64)
                lead[k][at] = fields.field(name).to_numpy()
            out: list[list] = [[], [], [], [], []]
            for lo, hi in _cuts(cols):
                root, side, tree = cols["root"][lo:hi], cols["side"][lo:hi], int(cols["tree"][lo])
                open_ = root[:, None] != root[None, :]
                if (side == 1).any():
                    open_ &= side[:, None] != side[None, :]
                elif cols["g2"][lo] & 1:
                    continue
                for k, trees in (("own", range(tree)), ("longer", range(TREES))):
                    for s in trees if k in lead else ():
                        v = lead[k][lo:hi, s]
                        open_ &= (v[:, None] != v[None, :]) | (v[:, None] < 0)
                kept = np.flatnonzero(open_.any(1))
                if len(kept):
                    for c, v in zip(out, (cols["g1"][lo:hi][kept], cols["g2"][lo:hi][kept], cols["rid"][lo:hi][kept], side[kept])):
                        c.append(v)
                    out[4] += _bits(open_[np.ix_(kept, kept)])
            if out[4]:
                yield pa.RecordBatch.from_arrays([*(pa.array(np.concatenate(c), x) for c, x in zip(out, (pa.int64(), pa.int64(), pa.int64(), pa.int32()))), pa.array(out[4], pa.binary())], ["g1", "g2", "rid", "side", "mask"])

    return run


_FOUND = "rid long, label long, n_texts long, n_docs long, " + ", ".join(f"p{r} double" for r in LEVELS)


def _least_labels(linked: np.ndarray, ids: np.ndarray) -> np.ndarray:
    labels = ids.copy()
    while True:
        new = np.minimum(labels, np.where(linked, labels[None, :], np.iinfo(np.int64).max).min(1))
        if (new == labels).all():
            return labels
        labels = new


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs of a group (of its two sides, if it has two; only those of the mask, if it has one): per text the texts and documents linked to it, the
    least text it hangs together with, and the sums of the probabilities with which its links meet at each level."""
    num, den = SIMILARITY.numerator, SIMILARITY.denominator
    for t in runs(batches, ["g1", "g2"], 4000):
        cols = {c: t.column(c).to_numpy() for c in ("g1", "g2", "rid", "side", "copies")}
        keys = [np.frombuffer(x, np.uint64) for x in t.column("keys").to_pylist()]
        masks = t.column("mask")
        out: list[list[np.ndarray]] = [[np.zeros(0, np.int64)] for _ in range(4)] + [[np.zeros(0)] for _ in LEVELS]
        for lo, hi in _cuts(cols):
            # a row that is repeated whole gives its set more than once
            at = lo + np.flatnonzero(np.concatenate([[True], np.diff(cols["rid"][lo:hi]) != 0]))
            rid, side = cols["rid"][at], cols["side"][at]
            n = len(at)
            left, right = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
            # the lowest bit of a group's number says that it has two sides
            two = bool(cols["g2"][lo] & 1)
            if n < 2 or (two and not (len(left) and len(right))):
                continue
            other = right if two else left
            common = overlaps([keys[at[k]] for k in left], [keys[at[k]] for k in right] if two else None)
            size = np.array([len(keys[k]) for k in at])
            total = size[left][:, None] + size[other][None, :]
            close = (common * (num + den) >= num * total) & (common > 0)
            likeness = np.where(close, common / np.maximum(total - common, 1), 0.0)
            full = np.zeros((n, n))
            full[np.ix_(left, other)] = likeness
            if two:
                full[np.ix_(other, left)] = likeness.T
            else:
                np.fill_diagonal(full, 0)
            if masks[lo].is_valid:
                wanted = np.unpackbits(np.frombuffer(b"".join(masks[int(k)].as_py() for k in at), np.uint8).reshape(n, -1), axis=1, count=n) > 0
                full[~wanted] = 0
            linked = full > 0
            hit = np.flatnonzero(linked.any(1))
            if not len(hit):
                continue
            linked, full = linked[np.ix_(hit, hit)], full[np.ix_(hit, hit)]
            out[0].append(rid[hit])
            out[1].append(_least_labels(linked, rid[hit]))
            out[2].append(linked.sum(1))
            out[3].append(linked @ cols["copies"][at][hit])
            for c, r in zip(out[4:], LEVELS):
                c.append(np.where(linked, meeting(full, r), 0.0).sum(1))
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in out], ["rid", "label", "n_texts", "n_docs", *(f"p{r}" for r in LEVELS)])


def _blocked(rows: DataFrame, key: list[str], g1: Column, g2: Column) -> DataFrame:
    """Groups of at most 2 * BLOCK texts: each pair of blocks of what has the same key, and each block with itself. The lowest bit of g2 says which."""
    sizes = rows.groupBy(*[F.col(c).alias(f"s_{c}") for c in key]).agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"), F.count("*").alias("many"))
    on = [F.col(c) == F.col(f"s_{c}") for c in key]
    sized = rows.join(sizes, on).where("many > 1").withColumn("block", F.pmod(F.xxhash64("rid"), "blocks").cast("int"))
    wide = sized.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    i, j = F.least("block", "other"), F.greatest("block", "other")
    pair = F.shiftleft(i.cast("long"), 20).bitwiseOR(j.cast("long"))
    two = (F.col("block") != F.col("other")).cast("long")
    side = ((F.col("block") > F.col("other"))).cast("int")
    return wide.select(*rows.columns, g1.alias("g1"), F.shiftleft(F.shiftleft(g2.cast("long"), 40).bitwiseOR(pair), 1).bitwiseOR(two).alias("g2"), side.alias("side"))


def _grouped(rows: DataFrame) -> DataFrame:
    return rows.repartition("g1", "g2").sortWithinPartitions("g1", "g2", "rid")


def _verified(groups: DataFrame, sets: DataFrame, name: str) -> DataFrame:
    """The links of groups of texts (g1, g2, rid, side, mask)."""
    groups = materialize(groups.select("g1", "g2", "rid", "side", "mask"), f"{name}_groups")
    few = groups.count() <= BROADCAST_ROWS
    whole = sets.join(F.broadcast(groups) if few else groups, "rid")
    return materialize(arrow_pass(_grouped(whole.select("g1", "g2", "rid", "side", "mask", "copies", "keys")), _verify, _FOUND), name)


def _first_links(met: DataFrame, sets: DataFrame) -> DataFrame:
    """Links of each text with the two texts that lead its runs most often, and with the two that stand before it most often."""
    own = F.array(*[F.when(F.col(f"l{r}") != F.col("rid"), F.col(f"l{r}")) for r in LEVELS])

    def most(values: Column) -> DataFrame:
        counted = met.select("rid", F.explode(values).alias("hub")).where("hub >= 0").groupBy("rid", "hub").agg(F.count("*").alias("n"))
        best = counted.groupBy("rid").agg(F.slice(F.sort_array(F.collect_list(F.struct("n", (-F.col("hub")).alias("h"))), False), 1, 2).alias("m"))
        return best.select("rid", F.explode("m").alias("m")).select("rid", (-F.col("m.h")).alias("hub"))

    stars = materialize(most(own).union(most(F.array("near"))).distinct(), "stars")
    parts = stars.groupBy("hub").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("parts"))
    number = lambda k: F.shiftleft(k.cast("long"), 1).bitwiseOR(F.lit(1).cast("long")).alias("g2")
    rays = stars.join(parts, "hub").select(F.col("hub").alias("g1"), number(F.pmod(F.xxhash64("rid"), "parts")), "rid", F.lit(0).alias("side"))
    hubs = parts.select("hub", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("k")).select(F.col("hub").alias("g1"), number(F.col("k")), F.col("hub").alias("rid"), F.lit(1).alias("side"))
    return _verified(rays.unionByName(hubs).withColumn("mask", F.lit(None).cast("binary")), sets, "stars")


def _edges(found: DataFrame) -> DataFrame:
    return found.where("rid <> label").select(F.col("rid").alias("u"), F.col("label").alias("v"))


def _met_again(met: DataFrame, marks: DataFrame, level: int, longer: int | None) -> DataFrame:
    """Groups of texts that share a prefix of this length in a tree, where texts of different clusters do and not all pairs share a longer one."""
    l, keep = f"l{level}", F.lit(True)
    at = met.where(F.col(l) >= 0)
    aggs = [F.min("root").alias("r_min"), F.max("root").alias("r_max")]
    if longer:
        deeper = F.col(f"l{longer}")
        mine = F.when(deeper >= 0, deeper).otherwise(F.col("rid"))
        aggs += [F.min(mine).alias("d_min"), F.max(mine).alias("d_max")]
        keep = F.col("d_min") != F.col("d_max")
    mixed = at.groupBy(F.col("tree").alias("m_tree"), F.col(l).alias("m_lead")).agg(*aggs).where((F.col("r_min") != F.col("r_max")) & keep).select("m_tree", "m_lead")
    rows = at.join(mixed, (F.col("tree") == F.col("m_tree")) & (F.col(l) == F.col("m_lead"))).select("rid", "tree", F.col(l).alias("lead"), "root")
    groups = _blocked(rows, ["tree", "lead"], F.col("lead"), F.col("tree"))
    names = ["tree", l] + ([f"l{longer}"] if longer else [])
    slim = marks.select("rid", F.transform("marks", lambda m: F.struct(*[m[c].alias(c) for c in names])).alias("marks"))
    return _grouped(groups.join(slim, "rid").select("g1", "g2", "rid", "side", "root", "tree", "marks"))


def _recall(found: DataFrame, level: int) -> float:
    """Recall of prefixes of this length for links as alike as those found, and one more at the threshold."""
    n, p = found.agg(F.sum("n_texts"), F.sum(f"p{level}")).first()
    return ((p or 0.0) / 2 + meeting(float(SIMILARITY), level)) / ((n or 0) / 2 + 1)


def links(texts: DataFrame, sets_of, recall: float = RECALL) -> tuple[DataFrame, DataFrame]:
    """(rid, n_docs) of linked texts and (node, root) of the classes that links make.

    `texts`: rid, n_windows, paths; `sets_of` gives rid, copies, keys of the texts of a
    table of rid.
    """
    spark = texts.sparkSession
    met = materialize(places(texts), "places")
    marks = materialize(met.groupBy("rid").agg(F.collect_list(F.struct("tree", *(f"l{r}" for r in LEVELS))).alias("marks")), "marks")
    sets = materialize(sets_of(marks.select("rid")), "sets")
    stars = _edges(_first_links(met, sets))
    clusters = materialize(components(stars), "clusters") if not stars.isEmpty() else spark.createDataFrame([], "node long, root long")
    inside = _blocked(clusters.select(F.col("node").alias("rid"), "root"), ["root"], F.col("root"), F.lit(0)).withColumn("mask", F.lit(None).cast("binary"))
    found = _verified(inside, sets, "inside")
    rooted = met.join(clusters.withColumnRenamed("node", "rid"), "rid", "left").withColumn("root", F.coalesce("root", "rid"))
    rooted = materialize(rooted.drop("near"), "rooted")
    every, crossing, longer = found, found.where("false"), None
    for level in reversed(LEVELS):
        # prefixes that are too long for the links found so far aren't tried
        if level > LEVELS[0] and _recall(every, level) < recall:
            continue
        pairs = arrow_pass(_met_again(rooted, marks, level, longer), _open_pairs(level, longer), _GROUP)
        new = _verified(pairs, sets, f"level{level}")
        every, crossing, longer = every.unionByName(new), crossing.unionByName(new), level
        if _recall(every, level) >= recall:
            break
    crossing = _edges(crossing)
    degree = materialize(every.groupBy("rid").agg(F.sum("n_docs").alias("n_docs")), "degree")
    if not crossing.isEmpty():
        clusters = materialize(components(clusters.select(F.col("node").alias("u"), F.col("root").alias("v")).union(crossing)), "classes")
    release(met, rooted, sets, marks)
    return degree, clusters


def join_texts(docs: DataFrame, recall: float = RECALL) -> DataFrame:
    """doc_id, class_id, n_links, n_copies, k1, k2, is_first of every row.

    Linked texts have five-word windows of Jaccard similarity 0.8 or more; a class is
    all texts that links (or equality) connect, its class_id the least doc_id in it.
    n_links counts the other rows linked directly: equal texts and similar ones;
    n_copies the other rows of equal text. is_first marks one row of each class.
    Null texts and texts without a word are alone; texts of one to four words link
    to equal texts only. Repeated rows count as copies. Texts are read whole, however
    long. Extra columns, whatever their names, are ignored. An empty table gives an
    empty result.
    """
    table = signed(docs.withColumn("text", F.when(F.col("text").rlike(r"[^\x20\x09-\x0D]"), F.col("text"))))
    # texts without a word: each row is a text of its own
    own = table.withColumn("salt", F.when(F.col("k1") == F.xxhash64(F.lit(None).cast("string")), F.col("rid")).otherwise(F.lit(-1)))
    texts = materialize(own.groupBy("k1", "k2", "salt").agg(F.min("rid").alias("rep"), F.count("*").alias("copies")), "texts")
    reps = table.join(texts.select(F.col("rep").alias("rid"), "copies"), "rid")

    def sets_of(wanted: DataFrame) -> DataFrame:
        place = materialize(reps.select("rid", "doc_id", "k1", "k2", "copies").join(wanted, "rid"), "wanted")
        body = docs.select(F.col("doc_id").cast("long").alias("b_doc"), *[k.alias(c) for c, k in zip(("b1", "b2"), text_key())], F.col("text").cast("string").alias("text"))
        few = place.count() <= BROADCAST_ROWS
        named = body.join(F.broadcast(place) if few else place.hint("shuffle_hash"), (body.b1 == place.k1) & (body.b2 == place.k2) & body.b_doc.eqNullSafe(place.doc_id))
        return arrow_pass(named.select("rid", "copies", "text"), _sets, "rid long, copies long, keys binary")

    degree, classes = links(reps, sets_of, recall)
    per_text = texts.join(degree.withColumnRenamed("rid", "rep"), "rep", "left").join(classes.select(F.col("node").alias("rep"), F.col("root").alias("label")), "rep", "left")
    per_text = per_text.select("k1", "k2", "salt", "rep", "copies", F.coalesce("label", "rep").alias("label"), F.coalesce("n_docs", F.lit(0)).alias("n_docs"))
    rows = materialize(own.select("rid", "doc_id", "k1", "k2", "salt").join(per_text, ["k1", "k2", "salt"]), "rows")
    least = rows.groupBy("label").agg(F.min("doc_id").alias("class_id"))
    first = F.col("rid") == F.col("label")
    return rows.join(least, "label").select("doc_id", "class_id", (F.col("copies") - 1 + F.col("n_docs")).alias("n_links"), (F.col("copies") - 1).alias("n_copies"), "k1", "k2", first.alias("is_first"))
