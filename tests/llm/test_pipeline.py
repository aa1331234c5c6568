"""The pipeline: each stage against what its operator says of its own input, and the whole run."""

import collections
import re

import pytest

import corpus_pipeline as C
from hitcodec.llm import decontaminate, ngram_join, toxicity
from hitcodec.llm.common import table
from hitcodec.llm.mixing import block_of
from hitcodec.session import scratch


@pytest.fixture(scope="module")
def steps(spark, sf):
    """The tables between the stages, each written and read again."""
    docs = table(spark, sf, "documents")
    found = [docs]
    for name, stage in C.STAGES:
        path = scratch(spark, f"test-{name}")
        stage(spark, docs, sf).write.parquet(path)
        docs = spark.read.parquet(path)
        found.append(docs)
    return found


def ids(df):
    return collections.Counter(r["doc_id"] for r in df.select("doc_id").collect())


def test_names():
    assert [n for n, _ in C.STAGES] == ["toxicity", "ngram_join", "decontaminate", "mixing", "token_output"]
    assert C.ORACLE_SQL is None


def test_columns(steps):
    for df in steps[1:-1]:
        assert df.columns == steps[0].columns


def test_toxic_go(spark, sf, steps):
    model = toxicity.fit(steps[0], table(spark, sf, "labels"))
    stay = {r["doc_id"] for r in toxicity.score(steps[0], model).where("score < 0.5").collect()}
    assert set(ids(steps[1])) == stay
    labels = {r["doc_id"]: r["toxic"] for r in table(spark, sf, "labels").collect()}
    clean = [d for d in ids(steps[0]) if labels.get(d) == 0]
    assert sum(d in stay for d in clean) >= 0.9 * len(clean)


def test_one_of_each_class_stays(steps):
    classes = collections.defaultdict(list)
    for r in ngram_join.ngram_join(steps[1]).collect():
        classes[r["class_id"]].append(r["doc_id"])
    assert ids(steps[2]) == collections.Counter(min(m) for m in classes.values())


def test_leaks_go(spark, sf, steps):
    bad = {r["doc_id"] for r in decontaminate.contaminated(steps[2], table(spark, sf, "benchmark")).collect()}
    assert set(ids(steps[3])) == set(ids(steps[2])) - bad


def test_mixed(steps):
    words = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t))
    before, after = collections.Counter(), collections.Counter()
    for df, c in ((steps[3], before), (steps[4], after)):
        for r in df.collect():
            c[r["source"]] += words(r["text"])
    total, names = sum(before.values()), sorted(before)
    weight = {s: k % 3 + 1 for k, s in enumerate(names)}
    free = {s for s in names if total * weight[s] / sum(weight.values()) < 2.9 * before[s]}
    shares = {after[s] / weight[s] for s in free}
    near = (3 + total // (4096 * block_of(total))) * block_of(total)  # a slot for each shard, and two blocks
    assert abs(sum(after.values()) - total) <= near * len(names)
    assert max(shares) - min(shares) <= 2 * near or len(free) < len(names)


def test_tokens(steps):
    last = steps[5].collect()
    assert ids(steps[5]) == ids(steps[4])
    at = 0
    for r in sorted(last, key=lambda r: r["start"]):
        assert r["start"] == at
        at += r["n_tokens"]


ODD = [
    (None, None, None, None), (1, "", "en", "a"), (2, "one two three", "en", None), (2, "one two three", "en", None), (3, "word " * 50_000, "de", "a"),
    (4, " \t\n", None, "b"), (None, "one two three", "en", "b"), (5, "some other words of a text that no one else has here", "en", "b"),
]
CLASH = "doc_id long, text string, lang string, source string, n_chars long, tk long, row string, label string, score double, bucket int"


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(*r, None if r[1] is None else len(r[1]), 7, "r", "l", 0.9, 1) for r in ODD], CLASH)


@pytest.mark.parametrize("name, stage", C.STAGES)
def test_odd_rows(spark, sf, odd, name, stage):
    """Nulls, empty and long texts, repeated rows, columns with names that the operators use, and no rows at all."""
    got = stage(spark, odd, sf)
    none = stage(spark, odd.limit(0), sf)
    assert none.count() == 0 and none.columns == got.columns
    texts = collections.Counter((r["doc_id"], r["text"]) for r in got.collect()) if name != "token_output" else None
    every = collections.Counter((d, t) for d, t, _, _ in ODD)
    if name in ("toxicity", "decontaminate"):  # all of them are clean
        assert got.columns == odd.columns and texts == every
    elif name == "ngram_join":  # one of each group of copies; what has no words has no copies
        kept = collections.Counter(t for _, t in texts.elements())
        assert got.columns == odd.columns and kept["one two three"] == 1 and kept[ODD[4][1]] == 1 and sum(texts.values()) == len(ODD) - 2
    elif name == "mixing":
        assert got.columns == odd.columns and set(texts) and all(t and t.split() for _, t in texts)
    else:
        assert ids(got) == collections.Counter(d for d, _, _, _ in ODD)


def test_run(spark, sf, steps):
    assert C.run(spark, sf).count() == steps[5].count()
