"""The language parser is built by a task and passes the driver packed."""

import pickle

import numpy as np

from frontfill.llm import language_id as L


def test_driver_holds_the_parser_packed(spark, monkeypatch):
    """The tables are built in a task: here their building on the driver is an error."""
    samples = {"a": "the quick brown fox jumps over the lazy dog " * 9, "b": "der schnelle braune fuchs springt weit " * 9}
    want = L.CrossParser(samples)
    monkeypatch.setattr(L.CrossParser, "__init__", None)
    packed = L.packed_parser(spark, samples)
    back = pickle.loads(pickle.dumps(packed))
    assert isinstance(packed, L.Packed) and isinstance(packed.blob, bytes)
    assert np.array_equal(back.table, want.table) and back.names == want.names
    assert back.judge(["the lazy fox", "ein fuchs", ""]) == want.judge(["the lazy fox", "ein fuchs", ""])
