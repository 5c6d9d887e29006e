"""Pipeline stages that end in Python get small batches whoever writes what they return."""

import pytest

import corpus_pipeline
from vecmend.llm import byte_bpe, decontaminate
from vecmend.llm import common as C


@pytest.mark.parametrize(("stage", "module"), ((corpus_pipeline.drop_contaminated, decontaminate), (corpus_pipeline.encode_bytes, byte_bpe)))
def test_stages_give_python_small_batches(spark, monkeypatch, tmp_path, stage, module):
    most = 2 * C.BATCH_BYTES

    def strict(run):
        def wrapped(batches):
            def seen():
                for b in batches:
                    if b.nbytes > most:
                        raise ValueError(f"a batch of {b.nbytes} bytes")
                    yield b

            return run(seen())

        return wrapped

    monkeypatch.setattr(module, "in_slices", strict)
    spark.createDataFrame([("a", "some words that no text here holds")], "item_id string, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = spark.range(0, 3000, 1, 1).selectExpr("id AS doc_id", "repeat('word ', 2000) AS text")
    out = stage(spark, docs, str(tmp_path))
    out.write.format("noop").mode("overwrite").save()
    assert out.count() == 3000


def test_a_written_table_is_not_written_again(spark):
    once = C.durable(spark.range(5))
    mark = C.tables_written(spark)
    assert C.durable(once) is once and C.tables_written(spark) == mark
    assert C.durable(once.where("id > 1")).count() == 3
