"""Bounded batches and trimmed workers change no result."""

import numpy as np
import pyarrow as pa
import pytest

from pathloom.llm.ngram_join import jaccard_classes
from pathloom.llm.store import BATCH_BYTES, lean, small_batches

SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"


@pytest.fixture
def setting(spark):
    yield spark.conf
    spark.conf.unset(SETTING)


def test_batches_are_bounded_and_lower_bounds_stay(spark, setting):
    for before, after in ((str(1 << 30), str(BATCH_BYTES)), ("1000", "1000"), ("2k", "2k"), ("64m", str(BATCH_BYTES))):
        setting.set(SETTING, before)
        small_batches(spark)
        assert setting.get(SETTING) == after
    setting.unset(SETTING)
    small_batches(spark)
    assert setting.get(SETTING) == str(BATCH_BYTES)


def test_tiny_batches_give_the_same_classes(spark, setting):
    words = [f"w{i}" for i in range(300)]
    rows = [(i, " ".join(words[: 300 - i % 5])) for i in range(40)] + [(100, None), (101, ""), (102, "alone here now " * 2000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    whole = sorted(jaccard_classes(docs).collect())
    setting.set(SETTING, "500")
    assert sorted(jaccard_classes(docs).collect()) == whole
    assert {r["component_id"] for r in whole} == {0, 100, 101, 102}


def test_lean_keeps_batches_errors_and_early_ends():
    batch = pa.RecordBatch.from_arrays([pa.array(np.arange(3))], ["a"])
    assert list(lean(lambda b: (x for x in b))(iter([batch, batch]))) == [batch, batch]
    assert next(lean(lambda b: (x for x in b))(iter([batch]))) is batch

    def broken(batches):
        yield from batches
        raise ValueError("broken")

    with pytest.raises(ValueError, match="broken"):
        list(lean(broken)(iter([batch])))
