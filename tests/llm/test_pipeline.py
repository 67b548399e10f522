"""The corpus pipeline stage by stage."""

import random
from collections import Counter

import corpus_pipeline
import pytest
from flowlens.llm.common import materialize, table
from flowlens.llm.near_dup import near_duplicates
from flowlens.llm.toxicity import toxicity_scores, trained

from ..conftest import SF
from .test_operators import brute_components, brute_removed, brute_targets


@pytest.fixture(scope="module")
def stages(spark):
    docs, out = table(spark, SF, "documents"), []
    for _, f in corpus_pipeline.STAGES:
        out.append((docs, new := materialize(f(spark, docs, SF))))
        docs = new
    return out


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


def test_columns(stages):
    columns = stages[0][0].columns
    assert all(after.columns == columns and after.schema["text"].dataType == before.schema["text"].dataType for before, after in stages[:-1])


def test_toxic_documents_go(spark, stages):
    before, after = stages[0]
    scores = by_id(toxicity_scores(before, trained(spark, before, table(spark, SF, "labels"))))
    assert set(by_id(after)) == {i for i, r in scores.items() if r["score"] < 0.7}


def test_one_of_each_group_stays(stages):
    before, after = (by_id(df) for df in stages[1])
    ids = sorted(before)
    groups = brute_components([before[i]["text"] for i in ids])
    assert set(after) == {ids[c] for _, c in groups}
    assert near_duplicates(stages[1][1]).where("not kept").count() == 0


def test_repeats_are_cut(stages):
    before, after = (by_id(df) for df in stages[2])
    ids = sorted(before)
    for i, (n, gone, _, _) in zip(ids, brute_removed([before[i]["text"] for i in ids])):
        assert abs(len((after[i]["text"] or "").encode()) - (n - gone)) <= 8 * 3 and after[i]["n_chars"] == len(after[i]["text"] or "")


def test_mix_and_packing(stages):
    before, after = stages[3]
    words = lambda df: sum(len((r["text"] or "").split()) for r in df.select("text").collect())
    assert abs(words(after) / words(before) - 1.5) < 0.2
    packed = stages[4][1]
    assert packed.groupBy("doc_id").count().count() == after.select("doc_id").distinct().count()


def test_run(spark, stages):
    assert corpus_pipeline.run(spark, SF).count() == stages[-1][1].count()


AWKWARD = [
    (None, "no id at all", "en", "a", 5), (1, None, None, None, None), (2, "", "en", None, 0), (3, " \n\t", "en", "a", 3), (4, "tie tie tie", "en", "b", 11), (4, "tie tie tie", "en", "b", 11),
    (5, "tie tie tie", "de", "b", 11), (6, "long " * 60_000, "en", "a", 1), (7, "passage of words that comes back again and again in more than one text, " * 3 + "end one", "en", "b", 9),
    (8, "passage of words that comes back again and again in more than one text, " * 3 + "and then something else entirely follows here", "fr", "c", 9),
]
CLASHING = "doc_id long, text string, lang string, source string, n_chars long, rep string, component string, size string, key string, hot string, _s string, _h string, start string, seg string"


@pytest.mark.parametrize("stage", [f for _, f in corpus_pipeline.STAGES], ids=[n for n, _ in corpus_pipeline.STAGES])
def test_awkward_and_empty_tables(spark, stage):
    df = spark.createDataFrame([(*r, *"abcdefghi") for r in AWKWARD], CLASHING)
    out = stage(spark, df, SF)
    rows = out.collect()
    if stage is not corpus_pipeline.pack_sequences:
        assert out.columns == df.columns and {r["doc_id"] for r in rows} <= {r[0] for r in AWKWARD}
        assert all(r["_s"] == "f" and r["seg"] == "i" for r in rows)
    empty = stage(spark, df.limit(0), SF)
    assert empty.count() == 0


def test_what_stages_keep_of_awkward_rows(spark):
    df = spark.createDataFrame([(*r, *"abcdefghi") for r in AWKWARD], CLASHING)
    ids = lambda f: sorted((r["doc_id"] for r in f(spark, df, SF).select("doc_id").collect()), key=lambda i: -1 if i is None else i)
    assert ids(corpus_pipeline.drop_toxic) == [None, 1, 2, 3, 4, 4, 5, 6, 7, 8]
    assert ids(corpus_pipeline.drop_near_duplicates) == [None, 1, 2, 3, 4, 6, 7, 8]
    assert ids(corpus_pipeline.cut_repeats) == [None, 1, 2, 3, 4, 4, 5, 6, 7, 8]
    assert set(ids(corpus_pipeline.mix_sources)) >= {1, 2, 3}
    assert len({r["doc_id"] for r in corpus_pipeline.pack_sequences(spark, df, SF).collect()}) == 9


def test_mix_with_ids_in_several_sources(spark):
    rng = random.Random(1)
    words = lambda: " ".join("w" for _ in range(rng.randrange(1, 200)))
    rows = [(i, "abc"[i % 3], words()) for i in range(300)] + [(i, "abc"[(i + 1) % 3], words()) for i in range(100)]
    df = spark.createDataFrame(rows, "doc_id long, source string, text string")
    size = Counter()
    for _, s, t in rows:
        size[s] += len(t.split())
    taken = Counter()
    for r in corpus_pipeline.mix_sources(spark, df, SF).collect():
        taken[r["source"]] += len(r["text"].split())
    for s, goal in brute_targets(size).items():
        assert abs(taken[s] - goal) <= 200
    again = sorted(map(str, corpus_pipeline.mix_sources(spark, df.repartition(9), SF).collect()))
    assert again == sorted(map(str, corpus_pipeline.mix_sources(spark, df, SF).collect()))


def test_mix_shuffles_no_texts(spark):
    plan = corpus_pipeline.mix_sources(spark, table(spark, SF, "documents"), SF)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "SortMergeJoin" not in plan and "hashpartitioning" not in plan


def test_ids_that_hold_several_texts_pass_all_stages(spark):
    rng = random.Random(2)
    words = lambda n: " ".join(f"w{rng.randrange(5000)}" for _ in range(n))
    passage = words(60)
    rows = [(i % 20, f"{words(30)} {passage} {words(20)}", "en", "ab"[i % 2], 1) for i in range(60)] + [(3, None, "en", "a", 0), (3, None, "en", "a", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES:
        docs = materialize(stage(spark, docs, SF))
    assert {r["doc_id"] for r in docs.collect()} <= set(range(20)) and docs.count() > 0
