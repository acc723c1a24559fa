"""The corpus pipeline, stage by stage."""

import random

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from replica_sync.llm import jaccard_join
from replica_sync.llm.common import kept_as_table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = {"input": docs}
    for name, stage in corpus_pipeline.STAGES:
        docs = out[name] = kept_as_table(stage(spark, docs, sf), name)
    return out


def test_columns(stages):
    assert all(stages[name].columns == COLUMNS for name in ("quality", "near_duplicates", "secrets", "mixing"))
    assert "ids_sha256" in stages["byte_bpe"].columns


def test_quality_keeps_most_good_documents(spark, sf, stages):
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    good = stages["input"].join(labels.where("quality = 1"), "doc_id")
    kept = stages["quality"].join(labels.where("quality = 1"), "doc_id")
    assert kept.count() / good.count() > 0.95


def test_one_of_each_group_stays(stages):
    texts = {r["doc_id"]: r["text"] for r in stages["quality"].collect()}
    assert sorted(r["doc_id"] for r in stages["near_duplicates"].collect()) == leaders_by_hand(texts)


def test_rows_of_one_id_are_told_apart(spark, sf):
    """No text is lost that has no near copy, and a copy goes even if its id stands for another group."""
    words = " ".join(f"w{k}" for k in range(60))
    rows = [(0, words), (1, words), (1, "quite another text under the same id"), (1, "quite another text under the same id"), (2, None), (2, ""), (3, ""), (None, words)]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    kept = corpus_pipeline.distinct_documents(spark, docs, sf).collect()
    assert sorted(((r["doc_id"], r["text"] or "") for r in kept), key=repr) == sorted([(0, words), (1, "quite another text under the same id"), (2, ""), (3, ""), (None, words)], key=repr)


def leaders_by_hand(texts, width=5, percent=80):
    """The smallest id of each group, by comparing all pairs of sets of so many words."""
    sets = {}
    for i, text in texts.items():
        words = (text or "").encode().lower().split()
        sets[i] = {tuple(words[k : k + width]) for k in range(max(1, len(words) - width + 1))} if words else set()
    group = {i: i for i in sets}
    for i in sets:
        for j in sets:
            if i < j and group[i] != group[j] and sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                low, high = sorted((group[i], group[j]))
                group = {k: low if g == high else g for k, g in group.items()}
    return sorted(set(group.values()))


def test_groups_are_those_of_five_words_at_four_fifths(spark, sf):
    """A hundred words with two changed apart: similarity 86/106 by five words, but 92/104 < 0.9 by three."""
    r = random.Random(5)
    texts = {}
    for family in range(6):
        base = [f"w{family}x{k}" for k in range(100)]
        for edits in (0, 1, 2, 2, 3, 3, 5):
            own = list(base)
            for k in r.sample(range(10, 90, 8), edits):
                own[k] = f"new{len(texts)}x{k}"
            texts[len(texts)] = " ".join(own)
    for t in ("a b c d", "A  b c d", None):
        texts[len(texts)] = t
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in texts.items()], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    kept = sorted(row["doc_id"] for row in corpus_pipeline.distinct_documents(spark, docs, sf).collect())
    assert kept == leaders_by_hand(texts) != leaders_by_hand(texts, 3, 90)


def test_no_secrets_are_left(stages):
    from replica_sync.llm.secret_scan import scan_secrets

    assert stages["secrets"].count() == stages["near_duplicates"].count()
    assert scan_secrets(stages["secrets"]).where("n_assign + n_access + n_hex > 0").count() == 0


def test_mixing_repeats_whole_rows(stages):
    before = {r["doc_id"]: r["text"] for r in stages["secrets"].collect()}
    after = stages["mixing"].collect()
    assert after and all(before[r["doc_id"]] == r["text"] for r in after)


def test_run(spark, sf, stages):
    rows = corpus_pipeline.run(spark, sf).collect()
    assert len(rows) == stages["byte_bpe"].count() == stages["mixing"].count()


def test_odd_tables(spark, sf):
    odd = spark.createDataFrame([(1, None, None, None, None, 1), (2, "", "en", "s", 0, 1), (None, "no id here", "en", "s", 10, 1), (3, "twice the same text", "en", "s", 19, 1), (3, "twice the same text", "en", "s", 19, 1)], "doc_id bigint, text string, lang string, source string, n_chars bigint, size int").withColumn("a.b", F.lit(1))
    once = corpus_pipeline.distinct_documents(spark, odd, sf).collect()
    assert sorted(((r["doc_id"], r["text"]) for r in once), key=repr) == sorted([(1, None), (2, ""), (3, "twice the same text"), (None, "no id here")], key=repr)
    assert sorted(r["doc_id"] or 0 for r in corpus_pipeline.without_secrets(spark, odd, sf).collect()) == [0, 1, 2, 3, 3]
    for frame in (odd, odd.limit(0)):
        for name, stage in corpus_pipeline.STAGES:
            out = kept_as_table(stage(spark, frame, sf), f"odd-{name}")
            assert out.count() <= 3 * frame.count()
            if name != "byte_bpe":
                assert out.columns == odd.columns
