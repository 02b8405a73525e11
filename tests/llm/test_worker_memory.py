"""What tasks leave in the Python workers that later stages use."""

import pyarrow as pa
import public_tokenizers

from kinetrace.llm import packing


def test_pretokens_of_a_task_are_forgotten(spark):
    """A worker that has packed keeps its vocabulary, but not the pre-tokens it met."""
    words = spark.range(0, 64, 1, 8).selectExpr("id AS doc_id", "array_join(transform(sequence(1, 200), i -> hex(id * 1000 + i)), ' ') AS text")
    packing.token_pieces(words, public_tokenizers.path("byte_bpe_50k.json")).collect()

    def left(batches):
        for batch in batches:
            encoders = [*packing._ENCODERS.values()]
            yield pa.RecordBatch.from_pydict({"encoders": [len(encoders)], "kept": [sum(len(e.slots) for e in encoders)]})

    found = spark.range(0, 64, 1, 8).mapInArrow(left, "encoders bigint, kept bigint").collect()
    assert any(r.encoders for r in found) and not any(r.kept for r in found)
