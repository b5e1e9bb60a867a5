"""What Python workers hold: batches of bounded size, and nothing of other operators or of tasks that are over."""

import pyarrow as pa

from saferoute.llm import bpe_automaton, common, ngram_join, quality

from . import helpers as h


def test_texts_come_in_small_batches(spark):
    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], ["n", "size"])

    docs = h.docs(spark, ["x" * 20_000] * 1_000).coalesce(1)
    seen = common.over_batches(docs.select("doc_id", "text"), sizes, "n long, size long").collect()
    assert sum(r["n"] for r in seen) == 1_000
    assert max(r["size"] for r in seen) <= common.BATCH_BYTES + 100_000


def test_an_operator_drops_what_another_keeps(spark):
    docs = h.docs(spark, ["one two three"] * 8)
    bpe_automaton.encode(docs).collect()
    quality.statistics(docs).collect()

    def kept(batches):
        size = bpe_automaton.encoder.cache_info().currsize
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([size] * b.num_rows, pa.int32())], ["n"])

    seen = common.over_batches(docs.select("doc_id"), kept, "n int").collect()
    assert [r["n"] for r in seen] == [0] * 8
    assert [r["n_tokens"] for r in bpe_automaton.encode(docs).collect()] == [3] * 8  # made again


def test_word_hashes_go_after_signing(spark):
    import importlib

    ngram_join.signed(h.docs(spark, ["a b c d e f g"] * 8)).collect()

    def left(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([len(importlib.import_module("saferoute.llm.ngram_join")._hashes)] * b.num_rows, pa.int32())], ["n"])

    assert {r["n"] for r in spark.range(8).mapInArrow(left, "n int").collect()} == {0}
