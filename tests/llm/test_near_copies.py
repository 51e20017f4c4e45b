"""The stage that removes near copies."""

import random

from treesieve.llm import jaccard

WORDS = [f"{a}{b}" for a in "bcdfglmnprst" for b in ("an", "er", "ing", "ol", "us", "y")]


def prose(n, seed):
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) + str(r.randint(0, 99)) for _ in range(n))


def test_stage_removes_near_copies(documents, spark):
    base = prose(300, 70).split()
    rows = [(0, " ".join(base), "s")]
    for i in range(1, 9):  # 5 of some 300 five-word shingles differ from the first, up to 10 from one another
        w = list(base)
        w[i * 30] = "changed"
        rows.append((i, " ".join(w), "s"))
    far = list(base)
    far[20::20] = ["other"] * len(far[20::20])  # 14 changes of five shingles each: Jaccard 0.61
    rows += [(20, " ".join(far), "s"), (21, prose(300, 71), "s"), (22, "", "s"), (23, None, "s"), (None, prose(60, 72), "s")]
    left = [r["doc_id"] for r in jaccard.stage(spark, documents(rows), "").collect()]
    assert sorted(left, key=str) == [0, 20, 21, 22, None]


def test_links_are_those_of_all_pairs(documents):
    r = random.Random(8)
    base, rows = [prose(120, 80 + i).split() for i in range(4)], []
    for i in range(80):
        w = list(base[i % 4])
        for _ in range(r.randint(0, 6)):
            w[r.randrange(len(w))] = f"x{r.randint(0, 9)}"
        rows.append((i, " ".join(w), "s"))
    sets = [set(jaccard.shingle_hashes(t.encode(), 5).tolist()) for _, t, _ in rows]
    want = list(range(80))
    for _ in range(80):
        want = [min(want[j] for j in range(80) if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])) for i in range(80)]
    got = {x["doc_id"]: x["component_id"] for x in jaccard.classes(documents(rows)).collect()}
    assert [got[i] for i in range(80)] == want and 4 < len(set(want)) < 80


def test_copies_that_are_not_similar_enough_meet_few(documents, monkeypatch):
    r = random.Random(5)
    base, rows = prose(34, 90).split(), []
    for i in range(600):  # one word changed: five of 30 shingles, so that two such copies link only if much the same place changed
        w = list(base)
        w[r.randrange(len(w))] = f"z{i}"
        rows.append((i, " ".join(w), "s"))
    met, alike = [], jaccard.alike
    monkeypatch.setattr(jaccard, "alike", lambda pairs, one, *a: met.append(pairs.count()) or alike(pairs, one, *a))
    got = {x["doc_id"]: x["component_id"] for x in jaccard.classes(documents(rows)).collect()}
    sets = [set(jaccard.shingle_hashes(t.encode(), 5).tolist()) for _, t, _ in rows]
    want = list(range(600))
    close = [[j for j in range(600) if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])] for i in range(600)]
    for _ in range(10):
        want = [min(want[j] for j in c) for c in close]
    assert [got[i] for i in range(600)] == want and len(set(want)) > 300
    assert sum(met) < 16 * 600


def test_prefixes_lose_no_pair(spark):
    r = random.Random(6)
    sets = [sorted({r.randrange(40) for _ in range(r.randint(1, 30))}) for _ in range(60)]
    sets += [sorted({*s} ^ {r.randrange(40)}) or [7] for s in sets for _ in range(3)]
    df = spark.createDataFrame([(i, i, s) for i, s in enumerate(sets)], "id long, root long, shingles array<int>")
    got = {tuple(x) for x in jaccard.prefix_pairs(df).collect()}
    near = {(i, j) for i, a in enumerate(sets) for j, b in enumerate(sets) if i < j and len({*a} & {*b}) >= 0.8 * len({*a} | {*b})}
    assert near <= got and len(near) > 100
