"""Text operators on small tables: edge cases, and what they are to find."""

import random
import uuid
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from treesieve.llm import bpe, chat, compaction, line_rules, mih, mixing, qda, simhash, suffix_dedup

RND = random.Random(5)
WORDS = [f"{a}{b}" for a in "bcdfglmnprst" for b in ("an", "er", "ing", "ol", "us", "y")]


def prose(n, seed):
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) + str(r.randint(0, 99)) for _ in range(n))


PASSAGE = prose(60, 1)
ODD = [(1, None, None), (2, "", "a"), (3, " \n\t", "a"), (4, "one", None), (5, prose(4000, 9), "a"), (6, prose(80, 10), "a"), (6, prose(80, 10), "a"), (None, prose(80, 11), "b")]


def test_edge_rows_pass_through_row_operators(documents, spark):
    docs = documents(ODD).withColumn("token_ids", F.lit("clash")).withColumn("score", F.lit(1))
    assert line_rules.judged(docs.select("doc_id", "text", "source")).count() == 8
    assert simhash.classes(docs).count() == 8
    assert bpe.decode(bpe.encode(docs)).select("decoded").collect()[3][0] == "one"
    labels = spark.createDataFrame([(2, 0, 0), (6, 1, 0), (5, None, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    assert qda.quality(docs, labels).where("score between 0 and 1").count() == 8
    mix = mixing.mixed(docs, labels)
    assert mix.count() == 8 and mix.where("rate < 0 or rate > 1").count() == 0


def test_empty_tables(documents, spark):
    docs = documents([])
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert simhash.classes(docs).count() == line_rules.judged(docs).count() == qda.quality(docs, labels).count() == 0
    assert suffix_dedup.repeats(docs).count() == mixing.mixed(docs, labels).count() == bpe.encode(docs).count() == 0
    assert chat.formatted(chat.neighbours(spark.createDataFrame([], "conv_id long, turn long, role string, text string"))).count() == 0


def test_boilerplate_lines(documents):
    rows = [(i, f"Read  more HERE\n{prose(60, 100 + i)}", "h") for i in range(30)] + [(99, "read more here", "h"), (98, prose(60, 1), "other")]
    got = {r["doc_id"]: r for r in line_rules.judged(documents(rows)).collect()}
    assert got[0]["n_removed_lines"] == 1 and got[0]["kept"] and "more" not in got[0]["text"]
    assert not got[99]["kept"] and got[99]["words_left"] == 0 and got[98]["n_removed_lines"] == 0


def test_near_copies_and_small_buckets(documents):
    base = prose(400, 3).split()
    rows = []
    for i in range(12):
        w = list(base)
        w[i * 7] = "changed"
        rows.append((i, " ".join(w), "s"))
    rows += [(50, prose(400, 4), "s"), (51, None, "s"), (52, "", "s")]
    found = {r["doc_id"]: r["component_id"] for r in simhash.classes(documents(rows), bucket=2).collect()}
    whole = {r["doc_id"]: r["component_id"] for r in simhash.classes(documents(rows)).collect()}
    assert found == whole and found[50] == 50 and found[51] == found[52] == 51 and len(set(found.values())) < len(rows)


def test_repeated_passages_are_cut_once(documents):
    rows = [(1, f"{prose(30, 21)} {PASSAGE} {prose(30, 22)}", "s"), (2, f"{prose(45, 23)}\n{PASSAGE}", "s"), (3, prose(200, 24), "s"), (4, " ".join(PASSAGE.split()[:49]), "s"), (5, None, "s"), (None, PASSAGE, "s")]
    docs = documents(rows)
    spans = suffix_dedup.repeats(docs)
    assert [tuple(r) for r in spans.collect()] == [(2, 45, 105, 60, 1)]
    left = {r["doc_id"]: r["text"] for r in suffix_dedup.without(docs, spans).collect()}
    assert left[1] == rows[0][1] and left[2].split() == prose(45, 23).split() and left[3] == rows[2][1]


def by_all_windows(rows, size=suffix_dedup.MIN_WORDS):
    """Word positions of each document that are in a window which stands earlier."""
    first, inside = {}, {}
    for doc, text, _ in sorted((r for r in rows if r[0] is not None), key=lambda r: r[0]):
        words = (text or "").split()
        for i in range(len(words) - size + 1):
            if first.setdefault(tuple(words[i : i + size]), (doc, i)) != (doc, i):
                inside.setdefault(doc, set()).update(range(i, i + size))
    return inside


def spread(spans):
    inside = {}
    for r in spans.collect():
        inside.setdefault(r["doc_id"], set()).update(range(r["start"], r["end"]))
    return inside


def test_passages_are_those_of_all_windows(documents, spark):
    r = random.Random(31)
    pool = [prose(n, 500 + n).split() for n in (48, 50, 51, 60, 75, 90, 140, 200)]
    rows = [(None, " ".join(pool[5]), "s"), (900, None, "s"), (901, "", "s"), (902, "a " * 300, "s"), (903, "b a " * 200, "s")]
    for i in range(150):
        words = []
        for _ in range(r.randint(1, 5)):
            piece = r.choice(pool)
            a = r.randint(0, len(piece) // 2)
            words += piece[a : r.randint(a + 1, len(piece))] if r.random() < 0.6 else prose(r.randint(1, 40), r.randint(0, 30)).split()
        rows.append((i, r.choice(["  ", "\n"]).join(words), "s"))
    rows += [(1000 + i, f"{prose(30, 2000 + i)} {PASSAGE} {prose(i % 40, 3000 + i)}", "s") for i in range(60)]  # one passage in many surroundings
    want = by_all_windows(rows)
    assert len(want) > 60 and any(len(x) > 100 for x in want.values())
    before = spark.conf.get("spark.sql.adaptive.coalescePartitions.enabled")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")  # so that orders have seams
    try:
        assert spread(suffix_dedup.repeats(documents(rows).withColumn("pos", F.lit("clash")))) == want
    finally:
        spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", before)


def test_neighbours_agree():
    rows = [b"aaaabbbbcccc", b"aaaabbbb", b"aaaabbbbdddd", b"", b"eeee"]
    assert suffix_dedup.agree(rows, 3).tolist() == [0, 2, 2, 0, 0] and suffix_dedup.agree(rows[:1], 3).tolist() == [0]


def test_search_ties_copies_and_missing(spark):
    v = [[(1.0 if RND.random() < 0.5 else -1.0) for _ in range(64)] for _ in range(30)]
    rows = [(i, v[i % 30]) for i in range(60)] + [(60, None), (None, v[0]), (61, [float("nan")]), (0, v[0])]
    codes = mih.binary_codes(spark.createDataFrame(rows, "vec_id long, embedding array<float>"))
    got = {}
    for r in mih.top_k(codes, codes.where("id % 20 = 0"), k=5, block_rows=7, block_queries=2).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["distance"], r["neighbour_id"]))
    bits = {i: [x > 0 for x in v[i % 30]] for i in range(60)} | {61: [False] * 64}
    ham = lambda a, b: sum(x != y for x, y in zip(bits[a], bits[b]))
    assert sorted(got) == [0, 20, 40, 60][:3]
    for q, best in got.items():
        assert best == sorted((ham(q, i), i) for i in bits)[:5]


def test_preference_pairs(spark):
    rows = [(0, 0, "user", "hi"), (0, 1, "assistant", "good"), (1, 0, "user", "hi"), (1, 1, "assistant", "bad"), (1, 2, "user", None), (2, 0, None, "lone"), (None, 0, "user", "x")]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r["pair_id"]: r for r in chat.formatted(chat.neighbours(turns)).collect()}
    a = got[0]
    assert a["prompt"] == "<|user|>\nhi<|end|>\n" and a["prompt_turns"] == 1
    start, end = map(int, a["chosen_mask"].split("-"))
    assert a["chosen"][start:end] == "good<|end|>\n" and a["rejected"].endswith("<|user|>\n<|end|>\n")
    assert got[1]["prompt"] == "" and got[1]["rejected"] == "" and got[1]["chosen"].startswith("<|unknown|>")
    pairs = spark.createDataFrame([(7, 1, 0), (8, 5, 6)], "pair_id long, chosen_id long, rejected_id long")
    general = {r["pair_id"]: r for r in chat.preference(turns, pairs).collect()}
    assert general[7]["chosen"] == a["rejected"] and general[8]["chosen"] == ""


def test_shards_versions_and_conflicts(documents, spark, tmp_path):
    store = compaction.ShardStore(spark, str(tmp_path / uuid.uuid4().hex), target=1 << 20, base=1 << 10, fanout=3)
    docs = documents(ODD)
    for _ in range(4):
        store.append(docs)
    before = store.manifest()
    with pytest.raises(compaction.Conflict):
        store.commit({"version": before["version"] - 1, "schema": None}, [], None)
    after = store.compact(finish=True)
    assert after["version"] > before["version"] and len(after["shards"]) < len(before["shards"])
    assert store.read().count() == 32 and store.read(before["version"]).count() == 32
    store.vacuum()
    assert store.read().exceptAll(docs.union(docs).union(docs).union(docs)).count() == 0 and store.versions() == [after["version"]]


def test_shards_of_other_columns(documents, spark, tmp_path):
    store = compaction.ShardStore(spark, str(tmp_path / uuid.uuid4().hex), target=1 << 20, base=1 << 10, fanout=2)
    docs = documents([(1, "a", "s"), (None, None, None)])
    store.append(docs.withColumn("extra", F.lit(7)))
    store.append(docs)
    store.append(docs.withColumn("later", F.lit("x")))
    store.append(documents([]))
    with pytest.raises(ValueError):
        store.append(docs.withColumn("extra", F.lit("text")))
    for _ in range(2):
        rows = store.read()
        assert rows.columns == [*docs.columns, "extra", "later"]
        assert sorted((r["extra"] or 0, r["later"] or "") for r in rows.collect()) == [(0, "")] * 2 + [(0, "x")] * 2 + [(7, "")] * 2
        store.compact(finish=True)


def test_clashing_names(documents):
    docs = documents(ODD)
    for n in [*line_rules.BASE, "_lines", "_row", "line"]:
        docs = docs.withColumn(n, F.lit("clash"))
    for broadcast in (10**6, 0):
        rows = line_rules.judged(docs, broadcast=broadcast).collect()
        assert len(rows) == 8 and all(r["line"] == "clash" and r["n_words"] != "clash" for r in rows)


def test_mix_reaches_its_targets(documents, spark):
    """The share of expected tokens that each domain has is its target, and the main domain is kept whole."""
    rows, labels = [], []
    for i in range(600):
        kind = ("clean", "low", "toxic")[0 if i % 10 < 6 else 1 if i % 10 < 8 else 2]
        text = prose(60, i) + " of the and" * 5 + {"clean": " fine" * 4, "low": " spam" * 4, "toxic": " bad" * 4}[kind]
        rows.append((i, text, "s"))
        labels.append((i, int(kind != "low"), int(kind == "toxic")))
    docs, named = documents(rows), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    mix = mixing.mixed(docs, named).cache()
    for r in mixing.reached(mix).collect():
        assert abs(r["share"] - r["target"]) < 0.01
    sums = {r["kind"]: r for r in mix.withColumn("kind", F.expr("case when doc_id % 10 < 6 then 'clean' else 'rest' end")).groupBy("kind").agg(F.avg("rate").alias("rate"), F.sum("copies").alias("copies")).collect()}
    assert sums["clean"]["rate"] > 0.99 and sums["rest"]["rate"] < 0.05 and sums["clean"]["copies"] > 350
    targets = {"clean": 0.4, "low": 0.3, "toxic": 0.3}
    more = mixing.mixed(docs, named, targets, max_rate=4.0)
    assert all(abs(r["share"] - r["target"]) < 0.02 for r in mixing.reached(more, targets).collect()) and more.agg(F.max("copies")).first()[0] > 1
    short = mixing.reached(mixing.mixed(docs, named, {"clean": 0.1, "low": 0.1, "toxic": 0.8}, total=1e6)).collect()
    assert next(r["share"] for r in short if r["domain"] == "toxic") < 0.8


def test_discriminant_is_the_formula(documents, spark):
    """Scores against a plain computation, and against held-out labels."""
    rows = [(i, prose(40, i) + (" !!! ###" * 6 if i % 3 == 0 else ""), "s") for i in range(300)]
    labels = spark.createDataFrame([(i, int(i % 3 != 0), 0) for i in range(300)] + [(5, 1, 0)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r for r in qda.quality(documents(rows), labels).collect()}
    x = {i: np.array(qda.statistics(t.encode())) for i, t, _ in rows}
    train = [i for i in [*x, 5] if zlib.crc32(str(i).encode()) % 5 != 0]
    classes = [np.array([x[i] for i in train if (i % 3 != 0) == k]) for k in (False, True)]
    cov = [np.cov(c.T, bias=True) for c in classes]
    shared = sum(len(c) * v for c, v in zip(classes, cov)) / len(train)
    for i in (0, 1, 2, 150, 299):
        logs = []
        for c, v in zip(classes, cov):
            v = (1 - qda.SHRINK - qda.POOL) * v + qda.SHRINK * np.diag(np.diag(v)) + qda.POOL * shared + qda.FLOOR * np.eye(len(v))
            z = x[i] - c.mean(axis=0)
            logs.append(-0.5 * z @ np.linalg.solve(v, z) - 0.5 * np.linalg.slogdet(v)[1] + np.log(len(c) / len(train)))
        assert got[i]["score"] == pytest.approx(1 / (1 + np.exp(logs[0] - logs[1])), abs=1e-6)
    held = [r for r in got.values() if r["held_out"]]
    assert len(held) > 30 and np.mean([r["predicted"] == int(r["doc_id"] % 3 != 0) for r in held]) > 0.95


def test_components_are_those_of_all_pairs(documents):
    r = random.Random(12)
    bases = [prose(300, 40 + i).split() for i in range(3)]
    rows = []
    for i in range(60):
        w = list(bases[i % 3])
        for _ in range(r.randint(0, 3)):
            w[r.randrange(len(w))] = r.choice(WORDS)
        rows.append((i, " ".join(w), "s"))
    fps = [simhash.majority(simhash.shingle_hashes(t.encode())) for _, t, _ in rows]
    want = list(range(60))
    for _ in range(60):
        want = [min(want[j] for j in range(60) if (fps[i] ^ fps[j]).bit_count() <= 2) for i in range(60)]
    got = {x["doc_id"]: x["component_id"] for x in simhash.classes(documents(rows)).collect()}
    assert [got[i] for i in range(60)] == want and 3 < len(set(want)) < 60


def test_empty_tables_of_the_others(documents, spark, tmp_path):
    codes = mih.binary_codes(spark.createDataFrame([], "vec_id long, embedding array<float>"))
    assert mih.top_k(codes, codes).count() == 0
    documents([]).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    assert compaction.query(spark, str(tmp_path)).count() == corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_pipeline_keeps_clean_documents(spark, documents, tmp_path):
    rows = [(i, prose(120, 1000 + i), "s") for i in range(40)] + [(100, prose(120, 1000), "s"), (101, "junk", "s")]
    documents(rows).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(i, 1, 0) for i in range(40)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    out = corpus_pipeline.run(spark, str(tmp_path))
    assert {r["doc_id"] for r in out.collect()} == set(range(40))
    assert [n for n, _ in corpus_pipeline.STAGES][0] == "quality_rules"
