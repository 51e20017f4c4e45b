"""Lines that repeat in a host of many documents."""

import random

from treesieve.llm import line_rules

PROSE = [f"{a}{b}" for a in "bcdfglmnprst" for b in ("an", "er", "ing", "ol", "us", "y")]


def prose(n, seed):
    r = random.Random(seed)
    return " ".join(r.choice(PROSE) + str(r.randint(0, 99)) for _ in range(n))


def test_copies_in_a_hot_host_go(documents, spark):
    banner, filler = "Share this page", "\n".join(f"{prose(8, 900 + i)}" for i in range(10))
    rows = [(i, prose(60, i), "hot") for i in range(400)]
    rows += [(400 + i, f"{banner}\n{prose(60, 400 + i)}", "hot") for i in range(20)]  # 20 of 436: within a tenth
    rows += [(500 + i, f"{filler}\n{prose(20, 500 + i)}", "hot") for i in range(16)]  # 80 of 100 words stand in 16 documents
    rows += [(600 + i, f"{banner}\n{prose(60, 600 + i)}", "small") for i in range(10)] + [(700, f"{banner}\n{prose(60, 700)}", None)]
    docs = documents(rows)
    left = {r["doc_id"]: r["text"] for r in line_rules.stage(spark, docs, "").collect()}
    assert not any(500 <= i < 600 for i in left) and len(left) == len(rows) - 16
    assert all(banner not in left[400 + i] for i in range(20)) and all(banner in left[i] for i in (*range(600, 610), 700))
    # the same by a shuffle of lines
    names = ["doc_id", "text", "n_removed_lines", "words_left", "kept"]
    few, many = (line_rules.judged(docs, most_docs=line_rules.MIN_DOCS, broadcast=b).select(names).collect() for b in (10**6, 0))
    assert sorted(few) == sorted(many)
