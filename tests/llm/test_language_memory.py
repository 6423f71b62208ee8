"""Language identification holds the n-grams of a small part of a batch at once."""

import tracemalloc

import pyarrow as pa

from hopframe.llm import language_id


def test_counting_a_large_batch_takes_little_memory():
    text = "".join(chr(97 + i * i % 26) + " " * (i % 5 == 0) for i in range(2_000))
    batch = pa.RecordBatch.from_arrays([pa.array(["en", "de"] * 1000), pa.array([text] * 2000)], ["lang", "text"])
    tracemalloc.start()
    counted = pa.Table.from_batches(language_id._counts(iter([batch]))).to_pydict()
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 64 << 20  # 387 MB in parts of 2 MB
    letters = [n for language, n in zip(counted["lang"], counted["n"]) if language == "en"]
    whole = pa.Table.from_batches(language_id._counts(iter([batch.slice(0, 1)]))).to_pydict()
    assert sum(letters) == 1000 * sum(whole["n"])
