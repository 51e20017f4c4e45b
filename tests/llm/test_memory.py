"""Python workers outlive their tasks; what they hold is there while other stages run."""

import shutil

import pyarrow as pa

from treesieve.llm import bpe


def test_encoding_leaves_no_vocabulary_in_its_workers(documents, spark, tmp_path):
    path = shutil.copy(bpe.vocabulary_path(), tmp_path / "own.json").as_posix()  # no other test's workers know it

    def held(batches):
        for batch in batches:
            before = bpe.trie.cache_info().hits
            bpe.trie(path)
            found = bpe.trie.cache_info().hits - before
            bpe.trie.cache_clear()
            yield pa.RecordBatch.from_arrays([pa.array([found] * batch.num_rows, pa.int64())], names=["n"])

    rows = documents([(i, f"some words of document {i}", "s") for i in range(8)])
    encoded = bpe.encode(rows, path=path, hold=False).collect()
    assert len(encoded) == 8 and all(len(r["token_ids"]) > 3 for r in encoded)
    assert max(r["n"] for r in spark.range(0, 8, 1, 8).mapInArrow(held, "n long").collect()) == 0
