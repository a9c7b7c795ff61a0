"""What a Python worker holds in a batch and after it."""

from __future__ import annotations

from pathlib import Path

import pyarrow as pa
import pytest

from tidegraph.llm import common, personal_data


class Table:
    """Stands in for a DataFrame: hands out the function of its mapInArrow."""

    def __init__(self, columns=()):
        self.columns, self.schema, self.sparkSession, self.sparkContext = list(columns), None, self, self

    def broadcast(self, value):
        self.value = value
        return self

    def mapInArrow(self, run, schema):  # noqa: N802
        return run


def _held() -> float:
    """MB of this process."""
    status = Path("/proc/self/status").read_text()
    return int(status.split("VmRSS:")[1].split()[0]) / 1024


@pytest.mark.skipif(common._trim() is None or not Path("/proc/self/status").exists(), reason="glibc on Linux")
def test_memory_goes_back_after_a_batch():
    pins = []

    def fn(batch):
        parts = [bytearray(64 << 10) for _ in range(4000)]  # 250 MB, with a piece that stays at the top
        pins.append(bytearray(64 << 10))
        for x in parts:
            x[::4096] = b"x" * 16
        return batch

    run = common.per_batch(Table(), fn, "")
    before = _held()
    assert sum(b.num_rows for b in run(iter([pa.record_batch([pa.array([1, 2])], names=["a"])]))) == 2
    assert _held() - before < 100


def test_texts_are_redacted_slice_by_slice():
    """A large batch goes out in small ones, every row in its place."""
    texts = [None if i % 50 == 7 else f"{i} mail joe.{i}@mail.example.com " + "plain words " * 400 for i in range(3000)]
    texts[5] = "x" * (5 << 20) + " joe@mail.example.com"
    whole = pa.record_batch([pa.array(range(3000)), pa.array(texts)], names=["doc_id", "text"])
    out = list(personal_data.find(Table(whole.schema.names), personal_data.trained(), output="text")(iter([whole, whole.slice(0, 0)])))
    assert len(out) > 4 and all(b.nbytes < 4 * common.SLICE_BYTES for b in out)
    got = pa.Table.from_batches(out)
    assert got["doc_id"].to_pylist() == list(range(3000))
    want = [None if t is None else t.replace(f"joe.{i}@mail.example.com", "[EMAIL]").replace("joe@mail.example.com", "[EMAIL]") for i, t in enumerate(texts)]
    assert got["text"].to_pylist() == want
