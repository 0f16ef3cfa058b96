"""The pipeline's stages in order, each held against what it must do to its own input."""

import hashlib
import random

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as pipeline
from embedvocab.llm import mixing, packing, quality_knn, substring_dedup, toxicity
from embedvocab.llm.common import written

NAMES = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def stages(spark, smoke):
    docs, out = spark.read.parquet(f"{smoke}/documents.parquet"), []
    for name, stage in pipeline.STAGES:
        made = written(stage(spark, docs, smoke))
        out.append((name, docs, made))
        docs = made
    return out


def test_order_and_columns(stages):
    assert [n for n, *_ in stages] == ["toxicity", "simhash near-dedup", "substring dedup", "source mixing", "packing"]
    assert all(made.columns == NAMES for _, _, made in stages[:-1])


def test_toxic_documents_go(spark, smoke, stages):
    _, docs, made = stages[0]
    model = toxicity.fit(docs, spark.read.parquet(f"{smoke}/labels.parquet"))
    want = sorted(r.doc_id for r in docs.collect() if model.score(r.text or "") < 0.3)
    assert sorted(r.doc_id for r in made.select("doc_id").collect()) == want


def jaccard(a, b):
    return len(a & b) / len(a | b) if a | b else 1.0


def shingles(text):
    w = text.lower().split()
    return {tuple(w[i:i + 5]) for i in range(len(w) - 4)} or {tuple(w)}


def test_near_copies_go(stages):
    _, docs, made = stages[1]
    before = {r.doc_id: shingles(r.text or "") for r in docs.collect()}
    kept = {r.doc_id for r in made.collect()}
    for i in kept:
        assert not any(j in kept and j < i and jaccard(before[i], before[j]) >= 0.8 for j in before)
    for i in set(before) - kept:
        assert any(j != i and jaccard(before[i], before[j]) >= 0.8 for j in before), i


def byte_shingles(text):
    w = (text or "").encode().lower().split()
    return {tuple(w[i:i + 5]) for i in range(len(w) - 4)} or {tuple(w)}


def test_near_copies_are_those_of_jaccard_0_8(spark, stages):
    """Edits of many strengths besides the stage's own input: exactly the documents that no chain of pairs of 0.8 or more joins to a lesser id stay."""
    r = random.Random(8)
    docs = {d.doc_id: d.text for d in stages[1][1].collect()}
    top = max(docs) + 1
    for group in range(40):
        words = [f"w{r.randrange(900)}" for _ in range(r.randint(40, 300))]
        for share in (0, *(r.uniform(0.01, 0.08) for _ in range(5))):
            docs[top] = " ".join(r.choice([f"e{r.randrange(900)}", w.upper()]) if r.random() < share else w for w in words)
            top += 1
    sets, root = {i: byte_shingles(t) for i, t in docs.items()}, {i: i for i in docs}
    where: dict = {}
    for i in sorted(sets):
        for x in sets[i]:
            where.setdefault(x, []).append(i)

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, own in sets.items():
        for j in {j for x in own for j in where[x] if j < i}:
            if len(own & sets[j]) / len(own | sets[j]) >= 0.8:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    df = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in docs.items()], "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(d.doc_id for d in pipeline.drop_near_copies(spark, df, "").collect()) == sorted(i for i in docs if find(i) == i)


def test_large_cells_are_compared_whole(spark, monkeypatch):
    from embedvocab.llm import simhash

    monkeypatch.setattr(simhash, "CELL", 8)
    r = random.Random(9)
    words = [f"w{i}" for i in range(200)]
    # most pairs of these lie below 0.8, so that the fragments of a cell are not joined at once
    texts = [" ".join(f"e{k}_{i}" if i in cut else w for i, w in enumerate(words)) for k in range(60) for cut in [set(r.sample(range(200), r.choice([1, 3, 6])))]]
    sets, root = [byte_shingles(t) for t in texts], list(range(60))
    for i in range(60):
        for j in range(i):
            if len(sets[i] & sets[j]) / len(sets[i] | sets[j]) >= 0.8:
                a, b = root[i], root[j]
                root = [min(a, b) if x in (a, b) else x for x in root]
    df = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(d.doc_id for d in simhash.keep_one(df).collect()) == sorted(set(root))


def test_repeats_go(stages):
    _, docs, made = stages[2]
    want = {i: (n, removed, sha) for i, n, removed, sha in substring_dedup.brute_force([(r.doc_id, r.text) for r in docs.collect()], pipeline.WINDOW)}
    got = {r.doc_id: r.text for r in made.collect()}
    assert set(got) == {i for i, (n, removed, _) in want.items() if not n or removed < n}
    assert all(hashlib.sha256(" ".join((t or "").split()).encode()).hexdigest() == want[i][2] for i, t in got.items() if t.isascii())


def test_mix_equals_the_query(spark, smoke, stages):
    _, docs, made = stages[3]
    scored = quality_knn.with_score(docs, quality_knn.fit(docs, spark.read.parquet(f"{smoke}/labels.parquet")), "score")
    taken = {r.doc_id: r.taken for r in mixing.digest(scored, weight=F.greatest(F.lit(0.05), F.col("score"))).collect()}
    got: dict[int, int] = {}
    for r in made.collect():
        got[r.doc_id] = got.get(r.doc_id, 0) + len((r.text or "").encode().split())
    assert got == {i: n for i, n in taken.items() if n or i in got}


def test_odd_rows_and_names(spark, smoke):
    """Null ids and texts, ids that repeat, and columns named like those that the stages make."""
    text = " ".join(f"w{i}" for i in range(60))
    rows = [(5, text, "en", "a", 1), (5, "all other words than those " * 9, "en", "a", 1), (1, text + " more", "en", None, 1), (9, "z y x " * 30, None, "b", 1), (9, "z y x " * 30, None, "b", 1),
            (None, None, None, None, None), (None, "no id " * 20, "en", "a", 1), (7, "", "en", "a", 0), (8, None, "en", "a", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for name in ("_near_id", "_id", "_hash", "_none", "node", "rest", "k", "_size", "_row", "score"):
        docs = docs.withColumn(name, F.lit(3))
    one = pipeline.drop_near_copies(spark, docs, smoke)
    assert one.columns == docs.columns
    # a text that shares an id with another stays; the nulls and the empty text are one group
    assert sorted((r.doc_id, (r.text or "")[:3]) for r in one.filter("doc_id is not null").collect()) == [(1, "w0 "), (5, "all"), (7, ""), (9, "z y")]
    assert one.filter("doc_id is null").count() == 1
    for _, stage in pipeline.STAGES[:-1]:
        made = stage(spark, docs, smoke)
        assert made.columns == docs.columns and made.count() > 0
    assert pipeline.pack_sequences(spark, docs, smoke).filter("doc_tokens = 1").count() == 3


def test_every_token_is_packed(stages):
    _, docs, made = stages[4]
    coder = packing.token_ids()
    want = sum(len(coder.encode(r.text or "")) // 4 + 1 for r in docs.collect())
    used = made.agg(F.sum("length").alias("n"), F.countDistinct("sequence_id").alias("s"), F.max(F.col("offset") + F.col("length")).alias("most")).first()
    assert used.n == want and used.most <= 1024 and used.s * 1024 < want + 1024 * 40


def test_run_gives_the_last_stage(spark, smoke, stages):
    got = pipeline.run(spark, smoke)
    assert sorted(r.ids_crc32 for r in got.collect()) == sorted(r.ids_crc32 for r in stages[-1][2].collect())


def test_empty_tables(spark, smoke):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in pipeline.STAGES:
        assert stage(spark, docs, smoke).count() == 0
