"""Predicted new facts: stand-in rankers, and moving candidates that break rules to the end."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.granule import TIME_COLUMNS
from ..plans.kg import KnowledgeGraph
from ..sources.tables import bucketed, small, written
from .detect import check_new_facts
from .score import TICKS, is_tick, tick_order, tick_verdict

#: A task is facts (fact_id, s, p, o, t): rank the properties p for (s, ?, o, t), or the objects o for (s, p, ?, t).


def split_by_time(facts: DataFrame, share: float = 0.8) -> tuple[DataFrame, DataFrame]:
    """The earliest share of facts by time, and the rest."""
    n = facts.count()
    k = int(n * share)
    bound = facts.orderBy("ts_lo", "fact_id").select("ts_lo", "fact_id").offset(k).limit(1).collect() if k < n else []
    if not bound:
        return facts, facts.limit(0)
    t, f = bound[0]
    early = (F.col("ts_lo") < t) | ((F.col("ts_lo") == t) & (F.col("fact_id") < f))
    return facts.where(early), facts.where(~early)


def hash_share(key: Column, seed: int = 0) -> Column:
    """A number in [0, 1) that SQL engines agree on."""
    return F.conv(F.substring(F.md5(F.concat(key, F.lit(f"#{seed}"))), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def resplit(train: DataFrame, valid: DataFrame, test: DataFrame, seed: int = 0) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Training part unchanged; the others mixed and halved at random, so that new facts needn't be the latest."""
    rest = valid.unionByName(test).withColumn("u", hash_share(F.col("fact_id"), seed))
    return train, rest.where("u < 0.5").drop("u"), rest.where("u >= 0.5").drop("u")


def _candidates(train: DataFrame, queries: DataFrame, slot: str) -> DataFrame:
    """Queries with their candidates: every property; of the objects, those seen with the subject, and the right one.

    Properties are as few as a schema has, and all are listed. Objects grow with the graph:
    those that the subject never had rank behind the others, so that places tell their ranks.
    """
    q = queries.select(F.col("fact_id").alias("qid"), "s", "p", "o", "ts_lo", F.col(slot).alias("gold"))
    pool = train.select(F.col(slot).alias("cand")).distinct()
    if slot == "p":
        return q.crossJoin(small(pool))
    seen = q.join(train.select("s", F.col("o").alias("cand")).distinct(), "s")
    right = q.withColumn("cand", F.col("gold")).join(pool, "cand", "left_semi")
    return seen.unionByName(right).distinct()


def _places(pool: DataFrame, order: list[Column]) -> DataFrame:
    """Place of every candidate in one order of all: ranges in order, counted, then numbered each for itself."""
    ranged = written(pool.repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "places")
    parts = ranged.groupBy("part").agg(F.count("*").alias("n"))
    before = parts.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"))
    numbered = ranged.withColumn("place", F.row_number().over(Window.partitionBy("part").orderBy(*order)))
    return numbered.join(small(before), "part").select("cand", (F.col("place") + F.col("before")).alias("place"))


def _ranked(scored: DataFrame, scores: list[str], places: DataFrame, slot: str) -> DataFrame:
    """Ranks among all candidates, listed or not: those with a score by their scores, then the others by place."""
    known = F.coalesce(*scores).isNotNull()
    all_ = scored.join(small(places) if slot == "p" else places, "cand").withColumn("known", known.cast("int"))
    q = Window.partitionBy("qid")
    first = F.row_number().over(q.orderBy(*[F.desc_nulls_last(c) for c in scores], "place"))
    ahead = F.sum("known").over(q) - F.sum("known").over(q.orderBy("place"))
    out = all_.withColumn("rank", F.when(known, first).otherwise(ahead + F.col("place")).cast("int"))
    return out.select("qid", "s", "p", "o", "ts_lo", F.col("cand").alias(f"cand_{slot}"), "rank", (F.col("cand") == F.col("gold")).alias("is_gold"))


def frequency_ranker(train: DataFrame, queries: DataFrame, slot: str = "p") -> DataFrame:
    """Candidates by how often they occurred with the query's pair, then its subject, then at all."""
    other = "o" if slot == "p" else "p"
    n = lambda keys, name: train.groupBy(*keys, F.col(slot).alias("cand")).agg(F.count("*").alias(name))
    c = _candidates(train, queries, slot)
    scored = c.join(n(["s", other], "n2"), ["s", other, "cand"], "left").join(n(["s"], "n1"), ["s", "cand"], "left")
    return _ranked(scored, ["n2", "n1"], _places(n([], "n0"), [F.desc("n0"), F.col("cand")]), slot)


def recency_ranker(train: DataFrame, queries: DataFrame, slot: str = "p") -> DataFrame:
    """Candidates by when they last occurred before the query with its pair, then with its subject."""
    other = "o" if slot == "p" else "p"
    c = _candidates(train, queries, slot).withColumn("qt", F.col("ts_lo"))
    past = lambda keys, name: (
        c.select("qid", "s", "p", "o", "qt", "cand").join(train.select(*keys, F.col(slot).alias("cand"), F.col("ts_lo").alias("at")), [*keys, "cand"]).where("at < qt").groupBy("qid", "cand").agg(F.max("at").alias(name))
    )
    scored = c.join(past(["s", other], "t2"), ["qid", "cand"], "left").join(past(["s"], "t1"), ["qid", "cand"], "left")
    return _ranked(scored, ["t2", "t1"], _places(train.select(F.col(slot).alias("cand")).distinct(), [F.col("cand")]), slot)


def external_ranking(queries: DataFrame, lists: DataFrame, slot: str = "p") -> DataFrame:
    """Predictions of another system as ranked candidates: `lists` has qid, cand and score; a greater score ranks first, ties by name.

    Rows of unknown queries or without a candidate are left out; a candidate listed twice counts once, with its greatest score.
    """
    q = queries.select(F.col("fact_id").alias("qid"), "s", "p", "o", "ts_lo", F.col(slot).alias("gold"))
    best = lists.where("cand is not null").groupBy("qid", "cand").agg(F.max("score").alias("score"))
    w = Window.partitionBy("qid").orderBy(F.desc_nulls_last("score"), "cand")
    ranked = q.join(best, "qid").withColumn("rank", F.row_number().over(w))
    return ranked.select("qid", "s", "p", "o", "ts_lo", F.col("cand").alias(f"cand_{slot}"), "rank", (F.col("cand") == F.col("gold")).alias("is_gold"))


def hypothetical_facts(predictions: DataFrame, slot: str = "p") -> DataFrame:
    """Each candidate filled into its query as an instant fact."""
    c = F.col(f"cand_{slot}")
    at = F.col("ts_lo")
    time = {"ts_lo": at, "ts_hi": at + 1, "ts_gran": F.lit(0).cast("tinyint"), "te_lo": at, "te_hi": at + 1, "te_gran": F.lit(0).cast("tinyint")}
    p, o = (c, F.col("o")) if slot == "p" else (F.col("p"), c)
    return predictions.select(F.concat_ws("|", F.lit("new"), "qid", c).alias("fact_id"), "s", p.alias("p"), o.alias("o"), F.lit("res").alias("o_kind"), *[time[x].alias(x) for x in TIME_COLUMNS], F.lit(True).alias("is_temporal"), F.lit("predicted").alias("src"))


def conflict_flags(kg: KnowledgeGraph, predictions: DataFrame, rules: DataFrame, slot: str = "p") -> DataFrame:
    """Candidates (qid, cand) whose fact breaks a rule against the graph."""
    new = hypothetical_facts(predictions, slot)
    hit = check_new_facts(kg, new, rules).select("new_fact").distinct()
    named = predictions.select("qid", f"cand_{slot}", F.concat_ws("|", F.lit("new"), "qid", F.col(f"cand_{slot}")).alias("new_fact"))
    return named.join(hit, "new_fact", "left_semi").select("qid", f"cand_{slot}")


def rerank(predictions: DataFrame, flags: DataFrame, slot: str = "p") -> DataFrame:
    """Flagged candidates move behind all others; within both groups the order stays."""
    marked = predictions.join(flags.distinct().withColumn("flag", F.lit(1)), ["qid", f"cand_{slot}"], "left").withColumn("flag", F.coalesce("flag", F.lit(0)))
    w = Window.partitionBy("qid").orderBy("flag", "rank")
    return marked.withColumn("new_rank", F.row_number().over(w))


def property_names(facts: DataFrame) -> DataFrame:
    """Properties numbered by name: p, name. They are as few as a schema has."""
    few = written(facts.where("p is not null").select(F.col("p").alias("name")).distinct(), "properties")
    return written(few.select(F.row_number().over(Window.orderBy("name")).alias("p"), "name"), "names")


def laid_by_subject(facts: DataFrame, names: DataFrame, held: Column) -> DataFrame:
    """Facts once, by subject: s, p (a number), o, fact, ts_lo, span, held, fact_id.

    Subjects, objects and ids are 64-bit hashes; facts held back have their ids instead. `span` has times that aren't single ticks.
    """
    marked = facts.join(small(names.withColumnRenamed("p", "number")), F.col("p") == F.col("name"), "left")
    hashed = [F.when(F.col(c).isNotNull(), F.xxhash64(c)).alias(a) for c, a in (("s", "s"), ("o", "o"), ("fact_id", "fact"))]
    marked = marked.select(*hashed, F.col("number").alias("p"), "ts_lo", F.when(~is_tick(), F.struct(*TIME_COLUMNS)).alias("span"), "fact_id", held.alias("held"))
    ids = {"fact_id": F.when(F.col("held"), F.col("fact_id")), "fact": F.when(~F.col("held"), F.col("fact"))}
    return bucketed(marked.withColumns(ids), "s", "facts")


def _breaking(rules: DataFrame, names: DataFrame) -> DataFrame:
    """cand, masks: by the property of an old fact, the TICKS of a new fact of cand to it that break some rule."""
    bits = lambda h, swapped: sum((F.when(v == -1, b).otherwise(0) for b, v in zip(TICKS, tick_verdict(h, swapped))), F.lit(0))

    def mask(swapped: bool) -> Column:
        out = F.lit(sum(TICKS))
        for h in ("start", "finish", "before", "disjoint", "include"):
            out = F.when(F.col("head") == h, bits(h, swapped)).otherwise(out)
        return out

    one = rules.where("pattern <> 'b' and d1 = 1 and d2 = 1")
    both = one.select(F.col("p1").alias("cand"), F.col("p2").alias("name"), mask(False).alias("mask")).unionAll(one.select("p2", "p1", mask(True)))
    each = both.groupBy("cand", "name").agg(F.bit_or("mask").alias("mask")).join(F.broadcast(names), "name")
    return each.groupBy("cand").agg(F.map_from_entries(F.collect_list(F.struct("p", "mask"))).alias("masks"))


def rerank_by_subject(laid: DataFrame, names: DataFrame, rules: DataFrame) -> DataFrame:
    """frequency_ranker, conflict_flags and rerank in one, for properties of facts laid by subject whose times are single ticks.

    Rules are of one subject, over forward slots and without classes. A held fact meets its subject's others
    in its own task: counts per property and the TICKS between them are all that ranks and flags need.
    Copies of a query are ranked as one list; an id belongs to one subject.
    """
    train = laid.where("not held")
    seen = train.groupBy("p").agg(F.count("*").alias("n0")).join(F.broadcast(names), "p").withColumnRenamed("name", "cand")
    seen = written(seen, "seen")
    places = _places(seen.select("cand", "n0"), [F.desc("n0"), F.col("cand")])
    pool = places.join(seen.select("cand", "p"), "cand").join(_breaking(rules, names), "cand", "left")
    pool = written(pool.agg(F.collect_list(F.struct("place", "cand", "p", "masks")).alias("pool")), "pool")
    q = laid.where("held").select("s", F.col("fact_id").alias("qid"), "p", "o", F.col("ts_lo").alias("at"), F.monotonically_increasing_id().alias("k"))
    t = train.select("s", F.col("p").alias("with"), F.col("o").alias("to"), F.col("ts_lo").alias("then"))
    met = q.join(t, "s", "left").groupBy("s", "k", "qid", "p", "with").agg(
        F.count("to").alias("n1"), F.count_if(F.col("o") == F.col("to")).alias("n2"), F.bit_or(F.when(F.col("o") != F.col("to"), tick_order(F.col("at"), F.col("then")))).alias("ticks")
    )
    # more facts of the pair come first, then more of the subject
    score = F.shiftleft("n2", 32) + F.col("n1")
    lists = met.groupBy("s", "qid").agg(F.collect_list(F.struct("k", "with", score.alias("score"), "ticks")).alias("met"), F.collect_set(F.struct("k", "p")).alias("copies"))

    def candidate(copy: Column, c: Column) -> Column:
        own = F.get(F.filter("met", lambda m: (m["with"] == c["p"]) & (m["k"] == copy["k"])), 0)["score"]
        broken = F.exists("met", lambda m: F.coalesce(m["ticks"].bitwiseAND(F.try_element_at(c["masks"], m["with"])), F.lit(0)) != 0)
        flag = F.when(c["masks"].isNotNull() & broken, 1).otherwise(0)
        return F.struct((-F.coalesce(own, F.lit(0))).alias("score"), c["place"].alias("place"), flag.alias("flag"), (c["p"] == copy["p"]).alias("is_gold"), c["cand"].alias("cand"))

    all_ = F.flatten(F.transform("copies", lambda copy: F.transform("pool", lambda c: candidate(copy, c))))
    ranked = lists.crossJoin(F.broadcast(pool)).select("qid", F.sort_array(all_).alias("all"))
    moved = F.sort_array(F.transform("all", lambda c, i: F.struct(c["flag"].alias("flag"), (i + 1).alias("rank"), c["is_gold"].alias("is_gold"), c["cand"].alias("cand"))))
    return ranked.select("qid", F.posexplode(moved).alias("at", "c")).select("qid", F.col("c.cand").alias("cand_p"), "c.rank", "c.is_gold", "c.flag", (F.col("at") + 1).alias("new_rank"))
