"""Quality rules: base counts of a text, and robust outliers among documents.

The base counts come from whole texts. Documents that pass the base rules are
judged per language and source: a minimum-covariance-determinant estimate of the
centre and spread of their transformed counts. Several starts take concentration
steps over all rows, the best go on until their determinants settle, and the least
determinant wins. A document is rejected when its squared robust distance is beyond
a quantile of the chi-square distribution.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_pass, broadcast_if_small, materialize
from .stats import chi2_above, chi2_cdf
from .textkernel import BLANK, per_doc, repeated, slices, span_hashes, windows, words_of, mix

SYMBOLS = np.zeros(256, bool)
SYMBOLS[list(b"#*$%&|<>")] = True

#: The five transformed counts, in order, and the least spread each is given.
FEATURES = ("f_words", "f_length", "f_symbols", "f_lines", "f_repeats")
FLOORS = (0.5, 0.08, 0.04, 0.1, 0.1)
_D = len(FEATURES)
#: Share of rows that the estimate covers, and the factor that makes it consistent where rows are normal.
COVER = 0.75
CONSISTENT = COVER / chi2_cdf(chi2_above(1 - COVER, _D), _D + 2)
#: Steps of all starts, starts that go on, change of the logarithm of the determinant at which one has settled, most steps.
FIRST_STEPS, GO_ON, SETTLED, MOST_STEPS = 2, 2, 1e-4, 30
#: Rows that a language's estimate weighs in that of each of its sources: ten for each free parameter of an estimate.
PRIOR_ROWS = 10 * _D * (_D + 3) // 2
#: Probability of a farther document, were the counts normal; squared distance beyond which a document is rejected.
TAIL = 1e-10
CUT = chi2_above(TAIL, _D)
#: Ranks of the distances in a group are exact up to this number of rows, beyond it to one in so many.
ACCURACY = 2000

_COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def count_texts(texts: pa.Array) -> dict[str, np.ndarray]:
    """The five base counts of each text."""
    out = {c: [np.zeros(0, np.int64)] for c in _COUNTS}
    for s in slices(texts):
        w = words_of(s)
        out["n_words"].append(np.diff(w.first))
        out["word_chars"].append(per_doc(~BLANK[s.buf] & ((s.buf & 0xC0) != 0x80), s.offsets))
        out["n_symbols"].append(per_doc(SYMBOLS[s.buf], s.offsets))
        # lines: cut at every line feed and at the ends of texts
        feeds = np.flatnonzero(s.buf == 10)
        starts = np.sort(np.concatenate([s.offsets[:-1], feeds + 1]), kind="stable")
        ends = np.sort(np.concatenate([feeds, s.offsets[1:]]), kind="stable")
        doc = np.repeat(np.arange(s.n), np.diff(np.searchsorted(feeds, s.offsets)) + 1)
        solid = np.searchsorted(w.start, ends) > np.searchsorted(w.start, starts)
        starts, ends, doc = starts[solid], ends[solid], doc[solid]
        keys = span_hashes(s.buf, starts, ends) ^ mix(doc.astype(np.uint64) + np.uint64(1))
        _, kept = np.unique(keys, return_index=True)
        out["n_dup_lines"].append(np.bincount(doc, minlength=s.n) - np.bincount(doc[kept], minlength=s.n))
        keys, at = windows(w, 5)
        at = at[repeated(keys ^ mix(w.doc[at].astype(np.uint64) + np.uint64(1)))]
        cover = np.zeros(len(w.hash) + 1, np.int64)
        cover[at] += 1
        np.add.at(cover, at + 5, -1)
        out["n_repeat_words"].append(per_doc(np.cumsum(cover[:-1]) > 0, w.first))
    return {c: np.concatenate(v) for c, v in out.items()}


def _counter(carried: list[str]):
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            counts = count_texts(b.column("text"))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in carried), *(pa.array(counts[c], pa.int64()) for c in _COUNTS)], [*carried, *_COUNTS])

    return count


def base_counts(docs: DataFrame, text: bool = False) -> DataFrame:
    """doc_id, lang, source, the base counts and base_failed; with text also the text, for a pass that filters. Null text counts as empty."""
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"), F.col("text").cast("string").alias("text"), *(["n_chars"] if text else []))
    carried = slim.columns if text else [c for c in slim.columns if c != "text"]
    fields = [*(f"{f.name} {f.dataType.simpleString()}" for f in slim.schema if f.name in carried), *(f"{k} long" for k in _COUNTS)]
    out = arrow_pass(slim, _counter(carried), ", ".join(fields))
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    return out.withColumn("base_failed", failed)


def _features() -> dict[str, Column]:
    words = F.greatest(F.col("n_words"), F.lit(1)).cast("double")
    return {
        "f_words": F.log1p("n_words"),
        "f_length": F.log(F.greatest(F.col("word_chars"), F.lit(1)) / words),
        "f_symbols": F.sqrt(F.col("n_symbols") / words),
        "f_lines": F.sqrt(F.col("n_dup_lines") / words),
        "f_repeats": F.sqrt(F.col("n_repeat_words") / words),
    }


_ESTIMATE = "g_lang string, g_key string, start int, n long, mu array<double>, cov array<double>, inv array<double>, logdet double"
_ARROW = pa.schema([("g_lang", pa.string()), ("g_key", pa.string()), ("start", pa.int32()), ("n", pa.int64()), ("mu", pa.list_(pa.float64())), ("cov", pa.list_(pa.float64())), ("inv", pa.list_(pa.float64())), ("logdet", pa.float64())])


def _finished(rows: list[tuple]) -> pa.RecordBatch:
    """Estimates with floors added to their spread, its inverse and the logarithm of its determinant."""
    out = []
    for lang, key, start, n, mu, cov in rows:
        cov = cov + np.diag(np.square(FLOORS))
        out.append((lang, key, start, n, mu.tolist(), cov.ravel().tolist(), np.linalg.inv(cov).ravel().tolist(), float(np.linalg.slogdet(cov)[1])))
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), _ARROW.types)] if out else [pa.array([], t) for t in _ARROW.types], schema=_ARROW)


def _moments(r: dict, prefix: str, n: float) -> tuple[np.ndarray, np.ndarray]:
    mu = np.array([r[f"{prefix}{i}"] for i in range(_D)]) / n
    cov = np.zeros((_D, _D))
    for i in range(_D):
        for j in range(i, _D):
            cov[i, j] = cov[j, i] = r[f"{prefix}{i}{j}"] / n - mu[i] * mu[j]
    return mu, cov


def _begin(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Four starts of each group: medians with robust scales, plain moments, moments of squashed rows, and of their directions."""
    for b in batches:
        rows = []
        for r in b.to_pylist():
            n, mid, scale = r["n"], np.array(r["mid"]), np.array(r["scale"])
            name = (r["g_lang"], r["g_key"])
            mu, cov = _moments(r, "s", n)
            rows += [(*name, 0, n, mid, np.diag(scale**2)), (*name, 1, n, mu, cov)]
            for k, prefix in ((2, "t"), (3, "u")):
                own = _moments(r, prefix, n)[1]
                unit = np.sqrt(np.maximum(np.diag(own), 1e-12))
                rows.append((*name, k, n, mid, own / np.outer(unit, unit) * np.outer(scale, scale)))
        yield _finished(rows)


def _refit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = []
        for r in b.to_pylist():
            mu, cov = _moments(r, "s", r["n"])
            rows.append((r["g_lang"], r["g_key"], r["start"], r["n"], mu, cov * CONSISTENT))
        yield _finished(rows)


def _parameters() -> list[Column]:
    """An estimate's arrays as columns of their own: plain doubles are what generated code is fast at."""
    pairs = [(i, j) for i in range(_D) for j in range(i, _D)]
    return [F.col("mu")[i].alias(f"m{i}") for i in range(_D)] + [(F.col("inv")[i * _D + j] * (1.0 if i == j else 2.0)).alias(f"v{i}{j}") for i, j in pairs]


def _distance() -> Column:
    diff = [F.col(f) - F.col(f"m{i}") for i, f in enumerate(FEATURES)]
    return sum((diff[i] * sum((diff[j] * F.col(f"v{i}{j}") for j in range(i + 1, _D)), diff[i] * F.col(f"v{i}{i}")) for i in range(_D)), F.lit(0.0))


def _sums(values: list[Column], prefix: str) -> list[Column]:
    return [F.sum(values[i]).alias(f"{prefix}{i}") for i in range(_D)] + [F.sum(values[i] * values[j]).alias(f"{prefix}{i}{j}") for i in range(_D) for j in range(i, _D)]


def _starts(good: DataFrame) -> DataFrame:
    x = [F.col(f) for f in FEATURES]
    quarters = [F.percentile_approx(f, [0.25, 0.5, 0.75], ACCURACY) for f in FEATURES]
    spread = good.groupBy(F.col("lang").alias("g_lang"), F.col("key").alias("g_key")).agg(*[q.alias(f"q{i}") for i, q in enumerate(quarters)])
    scale = F.array(*[F.greatest((F.col(f"q{i}")[2] - F.col(f"q{i}")[0]) / 1.349, F.lit(FLOORS[i])) for i in range(_D)])
    spread = materialize(spread.select("g_lang", "g_key", F.array(*[F.col(f"q{i}")[1] for i in range(_D)]).alias("mid"), scale.alias("scale")), "spread")
    rows = _named(good, broadcast_if_small(spread))
    z = [(x[i] - F.col("mid")[i]) / F.col("scale")[i] for i in range(_D)]
    rows = rows.withColumns({f"z{i}": z[i] for i in range(_D)})
    norm = F.greatest(F.sqrt(sum((F.col(f"z{i}") * F.col(f"z{i}") for i in range(_D)), F.lit(0.0))), F.lit(1e-9))
    rows = rows.withColumn("norm", norm)
    sums = _sums(x, "s") + _sums([F.tanh(f"z{i}") for i in range(_D)], "t") + _sums([F.col(f"z{i}") / F.col("norm") for i in range(_D)], "u")
    return arrow_pass(rows.groupBy("g_lang", "g_key").agg(F.count("*").alias("n"), F.first("mid").alias("mid"), F.first("scale").alias("scale"), *sums), _begin, _ESTIMATE)


def _named(rows: DataFrame, est: DataFrame) -> DataFrame:
    return rows.join(est, rows.lang.eqNullSafe(est.g_lang) & rows.key.eqNullSafe(est.g_key))


def _step(good: DataFrame, est: DataFrame, most: int) -> DataFrame:
    """A concentration step of every estimate, of which there are at most `most`: moments of the share COVER of its group that lies nearest."""
    lists = est.groupBy("g_lang", "g_key").agg(F.collect_list(F.struct("start", *_parameters())).alias("ests"))
    near = _named(good, broadcast_if_small(lists, most)).select("g_lang", "g_key", *FEATURES, F.inline("ests"))
    near = near.select("g_lang", "g_key", "start", *FEATURES, _distance().alias("d2"))
    limit = near.groupBy(F.col("g_lang").alias("l_lang"), F.col("g_key").alias("l_key"), F.col("start").alias("l_start")).agg(F.percentile_approx("d2", COVER, ACCURACY).alias("limit"))
    kept = near.join(broadcast_if_small(limit, most), near.g_lang.eqNullSafe(limit.l_lang) & near.g_key.eqNullSafe(limit.l_key) & (near.start == limit.l_start)).where(F.col("d2") <= F.col("limit"))
    moments = kept.groupBy("g_lang", "g_key", "start").agg(F.count("*").alias("n"), *_sums([F.col(f) for f in FEATURES], "s"))
    return arrow_pass(moments, _refit, _ESTIMATE)


def _best(est: DataFrame, n: int) -> DataFrame:
    """Of each group the n estimates of least determinant; ties by number of the start."""
    place = F.row_number().over(Window.partitionBy("g_lang", "g_key").orderBy("logdet", "start"))
    return est.withColumn("place", place).where(F.col("place") <= n).drop("place")


def fit(counted: DataFrame) -> DataFrame:
    """Estimates (g_lang, g_key, mu, inv) of sources (key 's' and the source) and of whole languages ('all').

    All starts take FIRST_STEPS concentration steps over all rows of their group; the
    GO_ON of least determinant go on until none changes it by more than SETTLED, and
    the least determinant wins. FLOORS are added to each spread, so that counts which
    hardly vary don't make it singular. A source's estimate is drawn towards its
    language's by the weight of PRIOR_ROWS rows, at every size of the source.
    """
    good = counted.where("not base_failed").select("lang", F.explode(F.array(F.concat(F.lit("s"), _source()), F.lit("all"))).alias("key"), *[c.alias(k) for k, c in _features().items()])
    good = materialize(good, "features")
    sizes = materialize(good.groupBy("lang", "key").agg(F.count("*").alias("rows")), "sizes")
    most = sizes.count()
    est = materialize(_starts(good), "starts")
    for _ in range(FIRST_STEPS):
        est = materialize(_step(good, est, 4 * most), "estimate")
    est = materialize(_best(est, GO_ON), "estimate")
    settled = []
    for _ in range(MOST_STEPS):
        old = est.select(F.col("g_lang").alias("o_lang"), F.col("g_key").alias("o_key"), F.col("start").alias("o_start"), F.col("logdet").alias("o_logdet"))
        new = _step(good, est, GO_ON * most)
        both = new.join(old, new.g_lang.eqNullSafe(old.o_lang) & new.g_key.eqNullSafe(old.o_key) & (new.start == old.o_start))
        both = materialize(both.select(*new.columns, (F.col("o_logdet") - F.col("logdet") > SETTLED).alias("still")), "estimate")
        settled.append(both.where("not still").drop("still"))
        est = both.where("still").drop("still")
        if est.isEmpty():
            break
    best = materialize(_best(reduce(DataFrame.unionByName, settled, est), 1), "best")
    whole = best.where("g_key = 'all'").select(F.col("g_lang").alias("w_lang"), F.col("mu").alias("w_mu"), F.col("cov").alias("w_cov"))
    both = best.join(broadcast_if_small(whole), best.g_lang.eqNullSafe(whole.w_lang)).join(sizes, best.g_lang.eqNullSafe(sizes.lang) & (best.g_key == sizes.key))
    weight = F.col("rows") / (F.col("rows") + F.lit(float(PRIOR_ROWS)))
    drawn = lambda c: F.zip_with(c, f"w_{c}", lambda a, b: weight * a + (1 - weight) * b).alias(c)
    return materialize(arrow_pass(both.select("g_lang", "g_key", drawn("mu"), drawn("cov")), _inverted, "g_lang string, g_key string, mu array<double>, inv array<double>"), "drawn")


def _inverted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        inv = [np.linalg.inv(np.array(c).reshape(_D, _D)).ravel().tolist() for c in b.column("cov").to_pylist()]
        yield pa.RecordBatch.from_arrays([b.column("g_lang"), b.column("g_key"), b.column("mu"), pa.array(inv, pa.list_(pa.float64()))], ["g_lang", "g_key", "mu", "inv"])


def _source() -> Column:
    return F.coalesce("source", F.lit("\0"))


def judge(counted: DataFrame, est: DataFrame, cut: float = CUT) -> DataFrame:
    """Add `distance` (null where the base rules reject) and `kept` by the estimate of the row's source."""
    est = broadcast_if_small(materialize(est.select("g_lang", "g_key", *_parameters()), "parameters"))
    rows = counted.withColumns({k: c for k, c in _features().items()}).withColumn("s_key", F.concat(F.lit("s"), _source()))
    both = rows.join(est, rows.lang.eqNullSafe(est.g_lang) & (rows.s_key == est.g_key), "left")
    far = both.withColumn("distance", F.when(~F.col("base_failed"), _distance()))
    return far.withColumn("kept", ~F.col("base_failed") & (F.coalesce("distance", F.lit(0.0)) <= cut)).select(*counted.columns, "distance", "kept")


def judge_documents(docs: DataFrame, cut: float = CUT) -> DataFrame:
    """Counts and verdict of every document.

    Null text counts as empty and fails the base rules, as do texts of fewer than
    ten words; null language or source is a group of its own. Texts are counted whole,
    however long. Repeated rows each get a row and each count in the estimates. Extra
    columns, whatever their names, are ignored. An empty table gives an empty result.
    """
    counted = materialize(base_counts(docs), "counts")
    out = judge(counted, fit(counted), cut)
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "distance", "kept")


def kept_documents(docs: DataFrame, cut: float = CUT) -> DataFrame:
    """doc_id, text, lang, source, n_chars of the documents that stay: a second pass over the texts filters, so none is shuffled."""
    est = fit(base_counts(docs))
    return judge(base_counts(docs, text=True), est, cut).where("kept").select("doc_id", "text", "lang", "source", "n_chars")
