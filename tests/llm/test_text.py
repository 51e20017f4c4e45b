"""Pieces of the text operators against brute force, without Spark."""

import random

import numpy as np
import pytest
import xxhash

from treesieve.llm import bpe, line_rules, mih, qda, simhash, suffix_dedup


def test_bpe_is_that_of_the_library():
    tokenizers = pytest.importorskip("tokenizers")
    path = bpe.vocabulary_path()
    t, ref, rnd = bpe.Trie(path, max_words=200), tokenizers.Tokenizer.from_file(path), random.Random(0)
    alpha = ["a", "b", "é", " ", "  ", "\n", "\t", "the", "ing", "'s", "0", "12", "<|endoftext|>", "<|endo", "漢字", "՘", "🙂", "\x1c", "\x85", "!!", "THE", "　"]
    texts = ["".join(rnd.choice(alpha) for _ in range(rnd.randint(0, 12))) for _ in range(1500)] + ["".join(rnd.choice("aabehilnorst ") for _ in range(60)) for _ in range(300)] + ["", "x" * 5000]
    ids, lengths = t.encode_batch(texts)
    want = [ref.encode(x, add_special_tokens=False).ids for x in texts]
    at = np.concatenate([[0], np.cumsum(lengths)])
    assert [ids[a:b].tolist() for a, b in zip(at[:-1], at[1:])] == want
    again = bpe.Trie(path)  # caches, and where the trie began, make no difference
    assert again.encode_batch(texts[::-1])[0].tolist() == [i for w in want[::-1] for i in w]
    assert t.decode_batch(ids.astype(np.int64), lengths) == [ref.decode(w, skip_special_tokens=False) for w in want]
    with pytest.raises(ValueError):
        t.decode_batch(np.array([10**6]), np.array([1]))


def test_fingerprints_and_links():
    rnd = random.Random(1)
    for n in (0, 1, 2, 3, 40, 700):
        words = [rnd.choice(["Aa", "b", "çé", "dd"]) for _ in range(n)]
        text = "  ".join(words)
        low = [w.replace("A", "a") for w in words]
        shingles = [" ".join(low[i : i + 3]) for i in range(max(1, n - 2))] if n else []
        h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
        want = sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h)) if h else 0
        assert simhash.majority(simhash.shingle_hashes(text.encode())) == want
    masks = simhash.variants(3)[0]
    assert all(bin(m & (1 << 64) - 1).count("1") >= 64 - 10 for _, m in masks)
    assert simhash.linked(np.array([0, 3, 15, 255 << 20], np.uint64)).tolist() == [0, 0, 0, 3]


def test_minimisers_meet():
    rnd = random.Random(2)
    for _ in range(40):
        words = [str(rnd.randint(0, 30)).encode() for _ in range(50)]
        a, b = ([str(rnd.random()).encode() for _ in range(rnd.randint(0, 40))] for _ in range(2))
        c = [str(rnd.random()).encode() for _ in range(rnd.randint(0, 40))]
        found = []
        for left in (a, b):
            text = [*left, *words, *c]
            at = suffix_dedup.kept_positions(suffix_dedup.Hashes(text), len(text)) - len(left)
            found.append({int(p) for p in at if 0 <= p <= 25})
        assert found[0] & found[1]


def test_base_rules():
    assert line_rules.shape(b"") == (0, 0, 0, 0, 0, True)
    assert line_rules.shape("a é #\na é #\n\n x".encode()) == (7, 7, 2, 1, 6, True)
    words = " ".join(f"w{i}" for i in range(60)).encode()
    assert line_rules.shape(words)[4:] == (0, False)
    assert line_rules.repeated_words(b"a b c a b c a".split()) == 7


def test_discriminant_and_search():
    assert len(qda.statistics(b"")) == len(qda.statistics(b"A b! | # 1\nx")) == len(qda.FEATURES)
    assert qda.Model(0.25).score(np.zeros((2, 3))).tolist() == [0.25, 0.25]
    rng = np.random.default_rng(0)
    codes = np.unique(rng.integers(0, 1 << 63, 300, dtype=np.int64).astype(np.uint64))
    t, weight = mih.Tables(codes), np.ones(len(codes), np.int64)
    for q in (int(codes[5]), 12345):
        at, far = t.nearest(q, weight, 7)
        d = np.bitwise_count(codes ^ np.uint64(q))
        assert sorted(far.tolist())[:7] == sorted(d.tolist())[:7] and (d[at] == far).all()
    assert len(t.nearest(1, weight, 10**6)[0]) == len(codes)
