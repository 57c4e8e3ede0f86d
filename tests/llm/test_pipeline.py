from collections import Counter, defaultdict

import corpus_pipeline as cp
from tempo_rules.llm import quality_rules

SF = "/root/testdata/sf0.001"


def test_stages_keep_columns_and_decide(spark):
    """Every stage over what the one before kept, each decision compared with its operator's own answer."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    seen = [docs]
    for name, stage in cp.STAGES:
        out = cp.materialize(stage(spark, seen[-1], SF), name)
        if name != cp.STAGES[-1][0]:
            assert sorted(out.columns) == sorted(docs.columns)
        seen.append(out)
    ids = [Counter(r["doc_id"] for r in d.select("doc_id").collect()) for d in seen]
    kept = {r["doc_id"] for r in quality_rules.judge_documents(docs).where("kept").collect()}
    assert set(ids[1]) == kept
    from tempo_rules.llm.near_duplicates import join_texts

    classes = defaultdict(set)
    for r in join_texts(seen[1]).collect():
        classes[r["class_id"]].add(r["doc_id"])
    assert set(ids[2]) <= set(ids[1]) and all(len(c & set(ids[2])) == 1 for c in classes.values())
    from tempo_rules.llm.decontamination import contaminated

    dirty = {r["doc_id"] for r in contaminated(seen[2], spark.read.parquet(f"{SF}/benchmark.parquet")).collect()}
    assert set(ids[3]) == set(ids[2]) - dirty and dirty
    from tempo_rules.llm.mixing import mix_documents

    copies = {r["doc_id"]: r["copies"] for r in mix_documents(seen[3]).collect()}
    assert ids[4] == Counter({d: c for d, c in copies.items() if c})
    assert ids[5] == ids[4]
    shards = defaultdict(list)
    for r in seen[5].select("shard", "slot").collect():
        shards[r["shard"]].append(r["slot"])
    assert all(sorted(s) == list(range(len(s))) for s in shards.values())


def test_repeated_rows_nulls_and_extra_columns(spark):
    long = " ".join(f"word{i} and" for i in range(40))
    rows = [(1, long, "en", "a", 9), (1, long, "en", "a", 9), (2, long, "en", "a", 9), (3, None, None, None, None), (None, " ".join(f"more{i} or" for i in range(30)), None, None, 3), (4, "short", "en", "b", 5)]
    docs = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, lang string, source string, n_chars long, rid long")
    one = cp.materialize(cp.quality_rules(spark, docs, SF))
    assert one.count() == 4
    two = cp.materialize(cp.near_duplicates(spark, one, SF))
    assert sorted(str(r["doc_id"]) for r in two.collect()) in (["1", "None"], ["2", "None"])
    four = cp.materialize(cp.mixing(spark, cp.decontamination(spark, two, SF), SF))
    assert set(four.columns) == set(cp.COLUMNS)
    assert cp.sharding(spark, four, SF).count() == four.count()


def test_empty_documents(spark):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in cp.STAGES:
        docs = cp.materialize(stage(spark, docs, SF), name)
    assert docs.collect() == []
