"""The pipeline's stages on the smallest tables, and the queries with SQL."""

import collections

import pytest

DATA = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet").cache()


def test_stages_keep_their_columns(spark, docs):
    import corpus_pipeline as p

    assert [n for n, _ in p.STAGES] == ["toxicity", "simhash", "suffixes", "mixing", "encoding"]
    got = docs
    for name, stage in p.STAGES[:-1]:
        before, got = got, stage(spark, got, DATA)
        assert got.columns == list(p.COLUMNS)
        got = got.cache()
        if name != "mixing":
            assert got.select("doc_id").distinct().count() == got.count() <= before.count()
        if name == "suffixes":
            assert got.count() == before.count()
    last = p.STAGES[-1][1](spark, got, DATA)
    assert last.count() == got.count() and last.where("NOT restored").count() == 0


def test_stages_take_odd_rows(spark, docs):
    import corpus_pipeline as p

    odd = [(None, None, None, None, None), (1, None, "en", None, 0), (1, "", "en", "s", 0), (1, "same text here", "en", "s", 14), (2, "same text here", "en", "s", 14)]
    df = spark.createDataFrame(odd, docs.schema)
    for _, stage in p.STAGES:
        assert stage(spark, df, DATA).count() <= 3 * len(odd)
        assert stage(spark, df.where("false"), DATA).count() == 0


def test_one_of_each_group_stays(spark, docs):
    import corpus_pipeline as p

    kept = {r["doc_id"] for r in p.simhash_stage(spark, docs, DATA).select("doc_id").collect()}
    texts = collections.defaultdict(list)
    for r in docs.collect():
        texts[r["text"]].append(r["doc_id"])
    for ids in texts.values():
        assert len(kept & set(ids)) <= 1


def test_sql(same_rows):
    from nzspan.llm import registry

    for name, sql in registry.oracle_sql().items():
        same_rows(registry.queries()[name], sql)


def test_no_near_copies_stay(spark, docs):
    import random

    import corpus_pipeline as p

    rng = random.Random(13)
    texts = [" ".join(f"w{rng.randint(0, 5000)}" for _ in range(rng.choice([3, 40, 150, 400]))) for _ in range(40)]
    for base in texts[:30]:
        for many in (1, 2, 3, 5, 8):
            words = base.split(" ")
            for _ in range(many):
                words[rng.randrange(len(words))] = f"n{rng.randint(0, 9999)}"
            texts.append(" ".join(words))
    line = " the same line stands at the end of every one of these texts as well"
    texts = [t + line for t in texts] + texts[:3] + ["", " ", "one two"]
    rng.shuffle(texts)

    def shingle_set(text):
        words = text.split()
        width = min(5, len(words))
        return {tuple(words[k : k + width]) for k in range(len(words) - width + 1)} if words else set()

    sets, up = [shingle_set(t) for t in texts], list(range(len(texts)))
    for b in range(len(sets)):
        for a in range(b):
            if up[a] != up[b] and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                low, high = sorted((up[a], up[b]))
                up = [low if u == high else u for u in up]
    df = spark.createDataFrame([(k, t, "en", "s", len(t)) for k, t in enumerate(texts)], docs.schema)
    assert {r["doc_id"] for r in p.simhash_stage(spark, df, DATA).collect()} == set(up)
