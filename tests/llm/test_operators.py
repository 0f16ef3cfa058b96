"""Each operator against its definition, on small tables with nulls, empty and long texts, ties and repeated rows."""

import hashlib
import random
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from embedvocab.llm import common, ctw, matroska, mixing, packing, quality_knn, simhash, spotsigs, substring_dedup, toxicity, warc

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def prose(seed, n):
    r = random.Random(seed)
    return " ".join(r.choice(["the", "of", "and"]) if r.random() < 0.3 else "".join(r.choice(["th", "er", "on", "an", "ing", "st"]) for _ in range(r.randint(2, 4))) for _ in range(n))


def odd_texts():
    passage = prose(99, 60)
    texts = [None, "", "   \n\t", "one", "one two", passage, "x " + passage, passage + " y z", prose(1, 34), prose(2, 35), prose(2, 35), "und " * 80, prose(3, 400) + " " + passage, prose(3, 400),
             "Ünï çödé ß 日本語 " * 12, "a\x0bb\x0cc\rd", "A B C a b c", prose(4, 3000), "<|endoftext|> marker  two spaces", "nbsp joined　words"]
    return [(i, t) for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", ["s1", "s2", None][i % 3], len(t) if t is not None else None) for i, t in odd_texts()]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def repeated(spark, docs):
    """Rows twice, null ids, and columns whose names the operators use themselves."""
    rows = docs.collect()
    more = [(None, "no id here " * 5, None, None, None)] * 2 + [tuple(r) for r in rows[:6]]
    out = spark.createDataFrame([tuple(r) for r in rows] + more, SCHEMA)
    for name in ("k", "rest", "bucket", "node", "_size", "target", "fp", "spans", "held_out", "_row"):
        out = out.withColumn(name, out.n_chars)
    return out


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


# ---------------------------------------------------------------- shared parts

@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 2**64 - 1)))
def test_packed_arrays(values):
    a = np.sort(np.array(values, np.uint64))
    assert (common.unpack(common.pack(a)) == a).all()


@settings(max_examples=60, deadline=None)
@given(st.lists(st.binary(max_size=40), min_size=1))
def test_words(texts):
    w = common.Words(texts)
    assert w.n.tolist() == [len(t.split()) for t in texts]
    words = [x for t in texts for x in t.split()]
    assert len(set(words)) == len(set(w.hash.tolist()))


# ---------------------------------------------------------------- 1 substring dedup

@pytest.mark.parametrize("window", [5, 35])
def test_substring_dedup(spark, docs, window):
    want = substring_dedup.brute_force(odd_texts(), window)
    assert sorted(map(tuple, substring_dedup.digest(docs, window).collect())) == sorted(want)


def test_substring_dedup_keeps_rows_and_columns(repeated, empty):
    out = substring_dedup.without_repeats(repeated)
    assert out.columns == repeated.columns and out.count() <= repeated.count()
    assert substring_dedup.digest(repeated).count() == repeated.count()
    assert substring_dedup.digest(empty).count() == 0 and substring_dedup.without_repeats(empty).count() == 0


def test_forced_hash_collisions_are_told_apart(monkeypatch):
    """With a first hash of 4 bits nearly all windows collide; the second, independent one still groups them by their words."""
    import pyarrow as pa

    monkeypatch.setattr(substring_dedup, "WINDOW_MASK", np.uint64(15))
    texts = [t or "" for _, t in odd_texts()] + [prose(40 + i % 7, 200) for i in range(20)]
    batch = pa.table({"doc_id": pa.array(range(len(texts)), pa.int64()), "text": pa.array(texts), "k": pa.array([0] * len(texts), pa.int32())})
    p = substring_dedup._Pass(batch, 8)
    p.probes()
    at, h, c = p.candidates(np.ones(len(p.block_at), bool))
    assert len(set(h.tolist())) <= 16
    words = [w for t in p.texts for w in t.split()]
    begin = substring_dedup._groups(h, c)
    for a, b in zip(begin, [*begin[1:], len(h)]):
        assert len({tuple(words[i:i + 8]) for i in at[a:b]}) == 1
    assert len(begin) == len({tuple(words[i:i + 8]) for i in at})


# ---------------------------------------------------------------- 2 media columns

@pytest.mark.parametrize("lacing", list(matroska.LACING))
def test_matroska_round_trip(lacing):
    for _, text in odd_texts():
        payload = matroska.payload_of((text or "").encode())
        media = matroska.mux(payload, lacing, blocks=3)
        packets, cues, tracks = matroska.parse(media)
        assert b"".join(media[o:o + s] for *_, o, s, _ in packets) == payload and tracks[1]["depth"] == 8
        assert [p[1] for p in packets] == [i * matroska.FRAME_MS * 1_000_000 for i in range(len(packets))]
        assert {c[2] for c in cues} == {p[2] for p in packets}


@pytest.mark.parametrize("kind", ["xiph", "ebml"])
def test_uneven_laces(kind):
    frames = [bytes([i]) * n for i, n in enumerate([0, 1, 254, 255, 256, 9000, 3, 70000])]
    body = matroska.laced(frames, kind)
    assert [body[o:o + s] for o, s in matroska.frame_ranges(body, 0, len(body), matroska.LACING[kind])] == frames


def test_unknown_sizes():
    media = matroska.mux(matroska.payload_of(b"abc" * 4000), blocks=1)
    at = media.index(matroska.SEGMENT.to_bytes(4, "big")) + 4
    _, end = matroska.read_vint(media, at, False)
    live = media[:at] + b"\x01" + b"\xff" * 7 + media[end:]
    assert len(matroska.parse(live)[0]) == len(matroska.parse(media)[0])
    with pytest.raises(ValueError):
        matroska.parse(media[:-5])


def test_matroska_columns(docs, repeated, empty):
    media = matroska.store(docs)
    assert matroska.packets(media).count() >= docs.count() and matroska.cue_points(media).count() >= docs.count()
    rows = {r.doc_id: r for r in matroska.digest(docs).collect()}
    for i, t in odd_texts():
        b = (t or "").encode()
        payload = b + b"\xff" * (max(576, -(-len(b) // 576) * 576) - len(b))
        assert (rows[i].n_bytes, rows[i].payload_bytes, rows[i].payload_sha256, rows[i].tail_crc32) == (len(b), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]))
    assert rows[9].media_sha256 == rows[10].media_sha256 and rows[9].feature == rows[10].feature
    assert matroska.digest(repeated).count() == repeated.count() and matroska.digest(empty).count() == 0


# ---------------------------------------------------------------- 3 WARC

def test_warc_rejects_magic_in_payloads(spark):
    inner = warc.record(7, "http://x/", b"inner", hashlib.sha1(b"inner").hexdigest(), None).decode()
    same = "y" * 1500
    pages = [(1, "http://a/", inner * 3), (2, None, None), (3, "http://b/\r\n", same), (4, "u", same), (5, "u", "short"), (6, "u", "short"), (8, "u", "z" * 5000 + inner), (None, "u", same), (9, "u", "é" * 3000)]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").withColumn("digest", spark.range(1).select("id").first().id + 0 * common.F.col("page_id"))
    rows = warc.read(warc.write(df, chunk=700, look_ahead=600), chunk=700).collect()
    got = {(r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in rows}
    want = set()
    for p, _, h in pages:
        b = (h or "").encode()
        refers = 4 if h == same and p != 4 else None
        want.add((p, len(b), hashlib.sha1(b).hexdigest(), "revisit" if refers else "response", refers))
    assert got == want and len(rows) == len(pages)


def test_warc_headers_of_any_length(spark):
    pages = [(i, f"http://h/{i}", "p%d" % i * 40) for i in range(20)] + [(30, "data:" + "a" * 70000, "long"), (31, "u", "after"), (32, "data:" + "b" * 3000, "z" * 2000), (33, "u", "last")]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").coalesce(1)
    want = sorted((p, len(h), hashlib.sha1(h.encode()).hexdigest()) for p, _, h in pages)
    for chunk, ahead in ((700, 600), (warc.CHUNK, warc.LOOK_AHEAD)):
        got = warc.read(warc.write(df, chunk=chunk, look_ahead=ahead), chunk=chunk).collect()
        assert sorted((r.page_id, r.payload_bytes, r.payload_digest) for r in got) == want


def test_warc_broken_chain_is_an_error(spark, tmp_path):
    body = b"".join(warc.record(i, "u", b"p%d" % i, "", None) for i in range(9))
    (tmp_path / "a.warc").write_bytes(body[:-7])
    with pytest.raises(Exception, match="the chain of records ends"):
        warc.read(warc.chunks_of_files(spark, str(tmp_path), chunk=1000, look_ahead=600), chunk=1000).collect()


def test_pointer_jumping():
    offset, after = np.array([0, 5, 10, 17, 30, 31]), np.array([10, 10, 30, 30, 99, 30])
    assert warc.reachable(offset, after).tolist() == [True, False, True, False, True, False]
    assert not warc.reachable(np.array([3]), np.array([9])).any() and len(warc.reachable(np.zeros(0, int), np.zeros(0, int))) == 0
    n = 1000
    assert warc.reachable(np.arange(n), np.arange(1, n + 1)).all()


def test_warc_empty_table(spark):
    assert warc.digest(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_warc_files(spark, tmp_path):
    body = b"".join(warc.record(i, "u", b"p%d" % i, hashlib.sha1(b"p%d" % i).hexdigest(), None) for i in range(40))
    (tmp_path / "a.warc").write_bytes(body)
    rows = warc.read(warc.chunks_of_files(spark, str(tmp_path), chunk=1000, look_ahead=600), chunk=1000).collect()
    assert sorted(r.page_id for r in rows) == list(range(40))


# ---------------------------------------------------------------- 4 packing

def test_packing(docs, repeated, empty):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    rows = packing.pack(docs, capacity=64).collect()
    by_doc, by_sequence = {}, {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_sequence.setdefault(r.sequence_id, []).append(r)
    for i, text in odd_texts():
        ids = t.encode(text or "", add_special_tokens=False).ids + [0]
        pieces = sorted(by_doc[i], key=lambda r: r.start)
        assert [p.start for p in pieces] == np.cumsum([0, *(p.length for p in pieces)])[:-1].tolist() and sum(p.length for p in pieces) == len(ids)
        for p in pieces:
            assert p.doc_tokens == len(ids) and p.ids_crc32 == zlib.crc32(np.array(ids[p.start:p.start + p.length], "<u4").tobytes())
    for own in by_sequence.values():
        own.sort(key=lambda r: r.offset)
        assert [p.offset for p in own] == np.cumsum([0, *(p.length for p in own)])[:-1].tolist() and sum(p.length for p in own) <= 64
    assert packing.pack(repeated).select("doc_id").count() >= repeated.count() and packing.pack(empty).count() == 0


@settings(max_examples=80, deadline=None)
@given(st.lists(st.integers(1, 63)))
def test_packing_wastes_less_than_a_sequence(lengths):
    pieces = packing.assign(lengths, 64, 1 / 64)
    assert [sum(n for _, n, _, _ in own) for own in pieces] == lengths
    assert len({at for own in pieces for _, _, at, _ in own}) <= -(-sum(lengths) // 64)


@settings(max_examples=80, deadline=None)
@given(st.lists(st.integers(1, 63), max_size=40))
def test_packing_takes_the_cheapest_sequence_with_room(lengths):
    """The rule in plain words: longest first, ties in order; lowest cost with room, ties to the first; else cut over the roomiest."""
    rooms, costs, want = [64] * -(-sum(lengths) // 64), [0.0] * -(-sum(lengths) // 64), [[] for _ in lengths]
    for doc in sorted(range(len(lengths)), key=lambda i: (-lengths[i], i)):
        left = lengths[doc]
        while left:
            fits = [i for i, r in enumerate(rooms) if r >= left] if left == lengths[doc] else []
            at = min(fits, key=lambda i: (costs[i], i)) if fits else max(range(len(rooms)), key=lambda i: (rooms[i], -i))
            n = min(left, rooms[at])
            want[doc].append((lengths[doc] - left, n, at, 64 - rooms[at]))
            rooms[at] -= n
            costs[at] += n + n * n / 64
            left -= n
    assert packing.assign(lengths, 64, 1 / 64) == want


@settings(max_examples=150, deadline=None)
@given(st.text(st.sampled_from(list("ab1 .,'\n\té日² ")), max_size=30))
def test_token_ids_equal_the_tokenizer(text):
    coder = packing.token_ids()
    assert np.frombuffer(coder.encode(text), "<u4").tolist() == coder.whole.encode(text, add_special_tokens=False).ids


# ---------------------------------------------------------------- 5 quality, 6 toxicity

def labelled(spark, n=400):
    rows, labels = [], []
    for i in range(n):
        bad, toxic = i % 4 == 0, i % 5 == 0
        text = "!! ".join(prose(i, 60).upper().split()) if bad else prose(i, 60)
        rows.append((i, text[:150] + (" you stupid zorblat " if toxic else " ") + text[150:], "en", "s", 1))
        labels.append((i, int(not bad), int(toxic)))
    labels += [(n + 1, 1, 0), (None, 1, 1), (2, None, None)]
    return spark.createDataFrame(rows, SCHEMA), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


@pytest.fixture(scope="module")
def both(spark):
    return labelled(spark)


def test_quality_on_held_out_rows(both, repeated, empty, spark):
    docs, labels = both
    model = quality_knn.fit(docs, labels)
    rows = [r for r in quality_knn.scores(docs, model).collect() if r.held_out]
    assert all(zlib.crc32(str(r.doc_id).encode()) % 5 == 0 for r in rows) and len(rows) > 30
    assert sum((r.score >= 0.5) == (r.doc_id % 4 != 0) for r in rows) / len(rows) > 0.95
    odd = quality_knn.scores(repeated, model).collect()
    assert len(odd) == repeated.count() and all(0 <= r.score <= 1 for r in odd)
    assert quality_knn.scores(empty, model).count() == 0
    none = quality_knn.fit(docs, labels.limit(0))
    assert {r.score for r in quality_knn.scores(repeated, none).collect()} == {0.5}


def test_toxicity_on_held_out_rows(both, repeated, empty):
    docs, labels = both
    model = toxicity.fit(docs, labels)
    rows = [r for r in toxicity.scores(docs, model).collect() if r.held_out]
    assert all(zlib.crc32(str(r.doc_id).encode()) % 4 == 2 for r in rows) and len(rows) > 30
    assert all(r.predicted == (r.doc_id % 5 == 0) for r in rows)
    assert "zorb*" in model.weights or "zorblat" in model.weights
    odd = toxicity.scores(repeated, model).collect()
    assert len(odd) == repeated.count() and all(0 <= r.score <= 1 for r in odd)
    assert toxicity.scores(empty, model).count() == 0
    kept = toxicity.keep_clean(docs, model)
    assert kept.columns == docs.columns and kept.filter("doc_id % 5 = 0").count() == 0 and kept.count() == 320
    assert toxicity.Model({}, []).score("nothing to see") == 0.0 and toxicity.fit(empty, labels).curve == []
    clean = repeated.withColumn("w", repeated.doc_id).withColumn("fold", repeated.doc_id)
    assert toxicity.keep_clean(clean, model).columns == clean.columns and toxicity.keep_clean(clean, model).count() == sum(not r.predicted for r in odd)


def test_quality_equals_brute_force(both, docs):
    model = quality_knn.fit(*both)
    texts = [t or "" for _, t in odd_texts()] + [r.text for r in both[0].limit(60).collect()]
    for t, s in zip(texts, model.score(texts), strict=True):
        assert abs(s - quality_knn.brute_force(model, t)) < 1e-4
    # the nearest vectors all tie: all of them vote
    tied = quality_knn.Model({"a": 0, "b": 1}, np.ones(2, np.float32), np.eye(2, dtype=np.float32), np.array([[1, 0]] * 4 + [[0, 1]] * 4, np.float32), np.array([1, 0, 0, 0, 1, 1, 1, 1.0]), 2)
    assert tied.score(["a a", "b"]).tolist() == [0.25, 1.0]


def test_quality_of_given_documents(spark):
    at = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{at}/documents.parquet"), spark.read.parquet(f"{at}/labels.parquet")
    for operator, label, share in ((quality_knn, "quality", 0.95), (toxicity, "toxic", 0.95)):
        rows = operator.scores(docs, operator.fit(docs, labels)).join(labels, "doc_id").filter("held_out").collect()
        assert sum(r.predicted == r[label] for r in rows) >= share * len(rows) > 0


def test_grammar_reads_clauses():
    m = toxicity.Model({}, [])
    total = lambda t: sum(m.clauses(t))
    plain, negated, reported, targeted = (total(t) for t in ("an idiot walks", "no idiot walks", "he said once more idiot", "idiot at you walks"))
    assert negated < plain < targeted and total("now said idiot") < plain and reported < targeted
    assert total("you are an idiot") > total("you idiot") > total("an idiot walks")
    assert total("I will kill you") > 4 * total("frost may kill the crop") > 0
    assert total("kill. you") == total("kill it") and total("idiotic") == 0 and total("xidiot") == 0 and total("") == 0


@settings(max_examples=150, deadline=None)
@given(st.lists(st.sampled_from("idiot scum kill hurt you them not never said wrote are is will shall a very walks home".split()), max_size=25))
def test_clause_equals_brute_force(words):
    m = toxicity.Model({"wal*": 1.7}, [])
    assert m.clause(words) == pytest.approx(toxicity.brute_force(words, m))


def test_composed_grammar_equals_its_parts():
    parts = [toxicity.countdown("negation", 3, 0.5, 1.0, ("insult",)), toxicity.latch("report", 0.7, ("insult", "threat")), toxicity.insults()]
    table = toxicity.compose(parts)
    r, state, states = random.Random(1), 0, [0, 0, 0]
    for _ in range(500):
        c = r.randrange(len(toxicity.CLASSES))
        state, factor = table[state][c]
        steps = [p.moves[s, toxicity.CLASSES[c]] for p, s in zip(parts, states, strict=True)]
        states = [s for s, _ in steps]
        assert factor == pytest.approx(steps[0][1] * steps[1][1] * steps[2][1])


def test_toxicity_of_very_long_texts_takes_linear_time():
    import time

    m = toxicity.Model({}, [])
    for unit in ("walks home idiot ", "walks home. "):
        began = time.process_time()
        m.score(unit * 60_000)
        short = time.process_time() - began
        began = time.process_time()
        m.score(unit * 600_000)  # 10 MB
        assert time.process_time() - began < 30 * short + 2


# ---------------------------------------------------------------- 7 SpotSigs

def plain_signatures(text):
    import re

    words = re.sub(r"[\W_]+", " ", text.lower()).split()
    content = [i for i, w in enumerate(words) if w not in spotsigs.ANCHORS]
    out = {(words[i - 1], words[i], words[j]) for i, j in zip(content, content[1:]) if i and words[i - 1] in spotsigs.ANCHORS}
    return out or set(zip(words, words[1:])) or {tuple(words)}


def test_spotsigs(docs, repeated, empty):
    rows = {r.doc_id: r for r in spotsigs.digest(docs).collect()}
    texts = [t or "" for _, t in odd_texts()]
    for i, t in enumerate(texts):
        nxt, half = texts[(i + 1) % len(texts)], len(t) // 2
        edited = t[:len(t) - half] + nxt[:half]
        a, b, c = map(plain_signatures, (t, edited, nxt))
        assert (rows[i].n_chars, rows[i].edited_sha256) == (len(t), hashlib.sha256(edited.encode()).hexdigest())
        assert rows[i].near_edited == pytest.approx(len(a & b) / len(a | b)) and rows[i].near_next == pytest.approx(len(a & c) / len(a | c)), t
    assert rows[9].fingerprint == rows[10].fingerprint
    assert spotsigs.digest(repeated).count() == repeated.count() and spotsigs.digest(empty).count() == 0


def test_spotsigs_pairs(spark):
    base = prose(7, 300)
    words = base.split()
    near = " ".join(w if i % 40 else "zzz" + w for i, w in enumerate(words))
    texts = [base, base, near, prose(8, 300), prose(9, 40), None]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    members, pairs = spotsigs.near_pairs(df, 0.7)
    sets = {r.doc_id: r.set_id for r in members.collect()}
    assert len(set(sets.values())) == 5
    want = {frozenset((sets[i], sets[j])) for i in range(6) for j in range(i) if sets[i] != sets[j] and (lambda a, b: len(a & b) / len(a | b) >= 0.7)(*(plain_signatures(texts[x] or "") for x in (i, j)))}
    assert {frozenset((r.a, r.b)) for r in pairs.collect()} == want and want
    plan = pairs._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan


def test_spotsigs_is_native(docs):
    plan = spotsigs.digest(docs)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan


def test_spotsigs_links(spark, repeated, empty):
    texts = [prose(7, 300), prose(7, 300), None, "", prose(9, 40), " ".join(w if i % 60 else "zz" + w for i, w in enumerate(prose(7, 300).split())), prose(11, 200)]
    df = spark.createDataFrame([(i + 1, t) for i, t in enumerate(texts)], "doc_id long, text string")
    sets = [frozenset(plain_signatures(t or "")) for t in texts]
    distinct = set(sets)
    want = [(i + 1, 1 + sets.index(s), sum(o != s and len(o & s) / len(o | s) >= 0.8 for o in distinct)) for i, s in enumerate(sets)]
    assert sorted(map(tuple, spotsigs.neighbours(df).collect())) == want and any(n for *_, n in want)
    assert spotsigs.neighbours(repeated).count() == repeated.count() and spotsigs.neighbours(empty).count() == 0


# ---------------------------------------------------------------- 8 SimHash

def test_simhash(spark, docs):
    rows = odd_texts()
    assert sorted(map(tuple, simhash.digest(docs).collect())) == sorted(simhash.brute_force(rows))


@pytest.mark.parametrize(("parts", "wide"), [(4, False), (5, False), (4, True), (6, True)])
def test_links_join_what_brute_force_joins(spark, parts, wide, monkeypatch):
    if wide:  # as with so many fingerprints that rows are cheap against candidates
        monkeypatch.setattr(simhash, "ROW_COST", 0.0)
        assert simhash.deepened([0.0, 9.0, 9.0], list(range(16)), 3, 5) == [(0.0, False), (9.0 * 4 / 4096, True), (9.0 * 4 / 4096, True)]
    r = random.Random(parts)
    seeds = [r.getrandbits(64) for _ in range(40)]
    fps = sorted({s ^ sum(1 << b for b in r.sample(range(64), r.randint(0, 5))) for s in seeds for _ in range(60)} | {0, 1, 2**64 - 1})
    signed = [int(np.uint64(f).view(np.int64)) for f in fps]
    nodes = spark.createDataFrame([(f, f) for f in signed], "node long, fp long")
    roots = {r.node: r.root for r in simhash.components(simhash.links(nodes, 3, range(parts, parts + 1))).collect()}
    parent = {f: f for f in signed}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    values = np.array(fps, np.uint64)
    for i in range(len(fps)):
        for j in np.flatnonzero(np.bitwise_count(values[i + 1:] ^ values[i]) <= 3) + i + 1:
            a, b = find(signed[i]), find(signed[int(j)])
            parent[max(a, b)] = min(a, b)
    classes, mine = {}, {}
    for f in signed:
        classes.setdefault(find(f), set()).add(f)
        mine.setdefault(roots.get(f, f), set()).add(f)
    assert sorted(map(sorted, classes.values())) == sorted(map(sorted, mine.values()))


def test_forest_splits_large_cells():
    r = np.random.default_rng(3)
    centre = r.integers(0, 2**63, 1, dtype=np.uint64)
    fps = np.unique(centre ^ (np.uint64(1) << r.integers(0, 64, 600, dtype=np.uint64)) ^ (np.uint64(1) << r.integers(0, 64, 600, dtype=np.uint64)))
    a, b = simhash.forest(np.zeros(len(fps), np.int64), simhash.within(fps, np.ones(len(fps), bool), 4))
    assert len(a) == len(fps) - 1


def test_a_row_is_sent_once_however_many_fingerprints_meet(spark, monkeypatch):
    """Large cells are divided inside their task: a second level of keys multiplies no rows, and joins what all pairs join."""
    r = np.random.default_rng(5)
    fps = np.unique(r.integers(0, 2**63, 3000, dtype=np.uint64) & r.integers(0, 2**63, 3000, dtype=np.uint64))
    nodes = spark.createDataFrame([(int(f), int(f)) for f in fps], "node long, fp long").repartition(2)
    monkeypatch.setattr(simhash, "ROW_COST", 0.0)  # as with so many fingerprints that rows are cheap against candidates
    plans = simhash.survey(nodes, ["fp"], 8, range(6, 7))
    rows = simhash.cells(nodes, ["fp"], plans)
    probes = sum(1 + len(simhash.flips(len(bits), t)) for bits, t in zip(plans[0].groups, plans[0].thresholds) if t >= 0)
    assert rows.count() <= probes * len(fps)
    seen = simhash.within(fps, np.ones(len(fps), bool), 8)
    one = np.zeros(len(fps), np.int64)
    keys = simhash.finer(fps, 8)
    assert keys is not None and len(keys) == 9
    whole, parted = (simhash.forest(one, seen, split) for split in (None, lambda at: simhash.finer(fps[at], 8)))
    labels = []
    for a, b in (whole, parted):
        label = np.arange(len(fps))
        simhash._merge(label, a, b)
        labels.append(label)
    assert len(whole[0]) > 20 and (labels[0] == labels[1]).all()


def test_thresholds_by_dynamic_programming():
    costs = [[0, 10, 100, 1000, 1e4], [0, 1, 2, 3, 1e4], [0, 50, 60, 70, 1e4]]
    got = simhash.allot(costs, 3)
    every = [(sum(c[t + 1] for c, t in zip(costs, (a, b, c3))), (a, b, c3)) for a in range(-1, 4) for b in range(-1, 4) for c3 in range(-1, 4) if a + b + c3 == 1]
    assert sum(c[t + 1] for c, t in zip(costs, got)) == min(every)[0] and sum(got) == 1


def test_radius_follows_from_the_similarity():
    assert simhash.radius_of(0.8) > simhash.radius_of(0.9) > simhash.radius_of(0.99) >= 0
    p = np.arccos(np.sqrt(0.8)) / np.pi
    draws = np.random.default_rng(1).binomial(64, p, (20_000, simhash.PRINTS))
    assert (draws.min(axis=1) > simhash.radius_of(0.8)).mean() <= simhash.MISS


def test_chain_of_links_is_one_component(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 101)], "a long, b long")
    assert {r.root for r in simhash.components(edges).filter("node <= 60").collect()} == {0}


def test_one_of_each_group_of_copies_stays(spark, repeated, empty):
    base = prose(21, 400)
    words = base.split()
    near = [" ".join("edit" if i == k * 37 + 5 else w for i, w in enumerate(words)) for k in range(4)]
    rows = [(10, base), (11, base), (12, near[0]), (13, near[1]), (14, near[2]), (20, prose(22, 400)), (21, prose(23, 400)), (22, None), (23, "")]
    df = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in rows], SCHEMA)
    assert sorted(r.doc_id for r in simhash.keep_one(df).collect()) == [10, 20, 21, 22]
    out = simhash.keep_one(repeated)
    assert out.columns == repeated.columns
    ids = [r.doc_id for r in out.collect()]
    assert len(ids) == len(set(ids)) and None in ids
    assert simhash.keep_one(empty).count() == 0 and simhash.digest(empty).count() == 0 and simhash.digest(repeated).count() == repeated.count()


# ---------------------------------------------------------------- 9 mixing

def test_targets_fill_up(spark):
    sizes = spark.createDataFrame([("a", 1000), ("b", 10), ("c", 0), (None, 500)], "source string, source_size long")
    got = {r.source: r.target for r in mixing.targets(sizes).collect()}
    # weights 1, 2, 3, 1: b and c are full at 30 and 0, the rest share 1480 evenly
    assert got == {"a": pytest.approx(740), "b": pytest.approx(30), "c": 0, None: pytest.approx(740)}


def test_mixing_meets_its_targets(spark, repeated, empty):
    r = random.Random(5)
    rows = [(i, prose(i, r.randint(0, 60)) or None, "en", ["a", "b", "c", "d", None][min(4, i % 7)], 1) for i in range(300)]
    df = spark.createDataFrame(rows, SCHEMA)
    got = mixing.digest(df).collect()
    by = {}
    for row, (_, t, _, s, _) in zip(sorted(got), rows, strict=True):
        assert row.size == len((t or "").split()) and 0 <= row.taken <= 3 * row.size
        by.setdefault(s, []).append(row)
    for own in by.values():
        assert abs(sum(x.taken for x in own) - own[0].target) <= 1 and own[0].source_size == sum(x.size for x in own)
    assert sorted(got) == sorted(mixing.digest(df.repartition(7)).collect())
    made = mixing.materialise(mixing.mix(df), df.columns)
    assert made.columns == df.columns and sum(len((x.text or "").split()) for x in made.collect()) == sum(x.taken for x in got)
    assert mixing.digest(repeated).count() == repeated.count() and mixing.materialise(mixing.mix(repeated), repeated.columns).columns == repeated.columns
    assert mixing.digest(empty).count() == 0 and mixing.materialise(mixing.mix(empty), empty.columns).count() == 0


# ---------------------------------------------------------------- 10 language model

def test_context_trees(docs, repeated, empty):
    rows = odd_texts()
    want = {w[0]: w for w in ctw.brute_force(rows)}
    got = {r.doc_id: r for r in ctw.scores(docs).collect()}
    for i, w in want.items():
        assert tuple(got[i])[:5] == w[:5]
        assert got[i].base_score == pytest.approx(w[5], abs=1e-6) and got[i].score == pytest.approx(w[6], rel=1e-5)
    assert ctw.scores(repeated).count() == repeated.count() and ctw.scores(empty).count() == 0


def test_estimates():
    n = np.array([0.0, 1, 3, 50, 2000])
    import math

    want = [math.lgamma(z + 0.5) + math.lgamma(2 * z + 0.5) - math.lgamma(3 * z + 1) - math.log(math.pi) for z in n]
    assert ctw.kt(n, 2 * n) == pytest.approx(want, abs=1e-9)


def test_probabilities_sum_to_one():
    text = [ctw.normalised(prose(1, 200).encode())]
    code, _ = ctw.grams(text, 3)
    distinct, n = np.unique(code, return_counts=True)
    levels = ctw.build(distinct, n.astype(float), 3, 0)
    for context in (code[100] >> np.uint64(8), np.uint64(0x010203)):
        every = (context << np.uint64(8)) | np.arange(256, dtype=np.uint64)
        assert np.exp(ctw.log_probability(every, levels)).sum() == pytest.approx(1.0)


# ---------------------------------------------------------------- very long texts, ties, repeated rows

@pytest.fixture(scope="module")
def very_long(spark):
    """Two texts of 2 MB that share half, their exact copy, and a short row: in one task of one table."""
    half = prose(50, 150_000)
    a, b = half + " " + prose(51, 150_000), prose(52, 150_000) + " " + half
    return spark.createDataFrame([(1, a, "en", "s", 1), (2, b, "en", "s", 1), (3, a, "en", "t", 1), (4, "short text", "en", None, 1)], SCHEMA).coalesce(1)


def test_very_long_texts(spark, both, very_long):
    texts = {r.doc_id: r.text for r in very_long.collect()}
    got = {r.doc_id: r for r in substring_dedup.digest(very_long).collect()}
    assert got[1].n_removed == got[1].n_words == got[3].n_removed and 150_000 <= got[2].n_removed < got[2].n_words and got[4].n_removed == 0
    media = {r.doc_id: r for r in matroska.digest(very_long).collect()}
    assert all(media[i].n_bytes == len(t.encode()) for i, t in texts.items()) and media[1].media_sha256 == media[3].media_sha256
    pages = very_long.selectExpr("doc_id as page_id", "'u' as url", "text as html")
    assert {r.page_id: (r.payload_bytes, r.record_type, r.refers_to) for r in warc.digest(pages).collect()}[1] == (len(texts[1].encode()), "revisit", 3)
    packed = packing.pack(very_long).collect()
    assert {i: sum(r.length for r in packed if r.doc_id == i) for i in texts} == {r.doc_id: r.doc_tokens for r in packed}
    for operator in (quality_knn, toxicity):
        scored = {r.doc_id: r.score for r in operator.scores(very_long, operator.fit(*both)).collect()}
        assert len(scored) == 4 and scored[1] == scored[3]
    spots = {r.doc_id: r for r in spotsigs.digest(very_long).collect()}
    assert spots[1].fingerprint == spots[3].fingerprint and spots[1].n_chars == len(texts[1])
    assert {r.doc_id: r.component_id for r in simhash.digest(very_long).collect()}[3] == 1
    assert sorted(r.doc_id for r in simhash.keep_one(very_long).collect()) == [1, 2, 4]
    assert {r.doc_id: r.size for r in mixing.digest(very_long).collect()}[2] == 300_000
    trees = {r.doc_id: r for r in ctw.scores(very_long).collect()}
    assert trees[1].score == trees[3].score < 0 and trees[1].n_tokens == 300_001


def test_ties_have_one_result(spark, both):
    """Rows alike in all that an operator looks at get the same results in any order and any partitioning."""
    rows = [(i, prose(i // 4, 80), "en", "s", 1) for i in range(24)]
    df = spark.createDataFrame(rows, SCHEMA)
    models = [(quality_knn, quality_knn.fit(*both)), (toxicity, toxicity.fit(*both))]
    for make in (lambda d: substring_dedup.digest(d, 20), matroska.digest, spotsigs.digest, simhash.digest, mixing.digest, lambda d: ctw.scores(d).select("doc_id", "n_known", "base_score", "score"),
                 simhash.keep_one, *(lambda d, o=o, m=m: o.scores(d, m) for o, m in models)):
        assert sorted(map(tuple, make(df).collect())) == sorted(map(tuple, make(df.orderBy(F.desc("doc_id")).repartition(3)).collect()))


def test_warc_rows_repeat_and_names_clash(spark):
    html = "x" * 1200
    rows = [(1, "u", html), (1, "u", html), (2, "u", html), (2, "u", html), (None, None, html), (3, "u", None)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    for name in ("digest", "archive", "chunk", "data", "offset", "payload_bytes", "refers_to", "record_type", "payload"):
        df = df.withColumn(name, F.lit(7))
    got = sorted((r.page_id or 0, r.record_type, r.refers_to) for r in warc.digest(df).collect())
    assert got == [(0, "revisit", 2), (1, "revisit", 2), (1, "revisit", 2), (2, "response", None), (2, "response", None), (3, "response", None)]
