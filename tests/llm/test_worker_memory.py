"""What a Python worker holds in and after a task of the pipeline."""

import gc
import re
from pathlib import Path
from types import SimpleNamespace

import pyarrow as pa
from pyspark.sql import types as T

from edgeloc.llm import common, piece_codec


def held_mb() -> float:
    return sum(map(int, re.findall(r"\nPss_(?:Anon|Shmem):\s+(\d+)", Path("/proc/self/smaps_rollup").read_text()))) / 1024


def encoder_run(texts: list[str]):
    """The generator that encode() hands to Spark, and its batch."""
    model = SimpleNamespace(value=piece_codec.PieceModel(piece_codec.default_model_path()))
    context = SimpleNamespace(broadcast=lambda _: model)
    docs = SimpleNamespace(sparkSession=SimpleNamespace(sparkContext=context), columns=["text"], schema=T.StructType([T.StructField("text", T.StringType())]), mapInArrow=lambda run, _: run)
    return piece_codec.encode(docs), pa.RecordBatch.from_arrays([pa.array(texts)], names=["text"])


def test_encoding_gives_its_memory_back():
    run, batch = encoder_run([" ".join(f"w{(k * 60 + j) * 7919 % 1_000_003:x}" for j in range(60)) for k in range(10_000)])
    gc.collect()
    before, peak, rows = held_mb(), 0.0, 0
    for out in run(iter([batch])):
        peak, rows = max(peak, held_mb()), rows + out.num_rows
        assert out.column(0).nbytes < 3 << 19  # a slice has about 1 MB of text
    del out
    after = held_mb()
    assert rows == 10_000 and peak - before > 60  # else it shows nothing
    assert after - before < 0.1 * (peak - before)


def test_released_passes_rows_and_errors_on():
    assert list(common.released(lambda b: (x + 1 for x in b))(iter([1, 2]))) == [2, 3]

    def fails(batches):
        yield next(batches)
        raise ValueError("as it was")

    got = common.released(fails)(iter([1]))
    assert next(got) == 1
    try:
        next(got)
    except ValueError as e:
        assert str(e) == "as it was"
    else:
        raise AssertionError
