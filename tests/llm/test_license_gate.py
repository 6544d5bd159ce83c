"""Texts that hold a detection but none of the other trigger words pass op10's outer gate."""

import pyarrow as pa
import pytest

from rgsketch.llm import license_scan

CASES = [
    ("Except as contained in this notice, the name of the X Consortium shall not be used in sales without prior written authorization", "x11"),
    ("The names of the authors shall not be used in advertising or otherwise to promote sales without prior\nwritten authorization", "mit-advertising"),
]


@pytest.mark.parametrize(("text", "label"), CASES)
def test_gate_lets_written_authorizations_pass(text, label):
    batch = pa.RecordBatch.from_pydict({"doc_id": pa.array([1]), "text": pa.array([text])})
    (out,) = license_scan._scan(iter([batch]))
    assert label in out.column(6).to_pylist()[0]
