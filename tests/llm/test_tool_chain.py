"""Long chains of calls that depend on later turns."""

from __future__ import annotations

from tracefl.llm import tool_calls


def test_a_chain_longer_than_64_calls(spark):
    n = 67
    calls = spark.createDataFrame([(1, i, f"t{i}", [f"t{i + 1}"] if i + 1 < n else []) for i in range(n)], "conv_id long, turn int, call_id string, depends_on array<string>")
    got = {r["call_id"]: r for r in tool_calls.places(calls).collect()}
    assert {r["place"] for r in got.values()} == {n - 1} and not any(r["cyclic"] for r in got.values())
    assert sorted(got, key=lambda c: got[c]["step"]) == [f"t{i}" for i in range(n - 1, -1, -1)]


HOSTILE = ['{"a": "\\ud800"}', "[" * 100_000 + "]" * 100_000, '{"n": ' + "9" * 401 + "}", '{"n": NaN}', '{"n": 1e999}', '{"n": -Infinity}', '{"\\udfff": 1}', "", None, "{}"]


def test_hostile_arguments(spark):
    import json

    schemas = {"f": {"type": "object", "additionalProperties": {"type": ["integer", "string"]}}, "g": {"type": "thing"}}
    rows = [(1, i, f"c{i}", "f", a, [], "x", i, i) for i, a in enumerate(HOSTILE)] + [(1, 50, "c50", "g", "{}", [None, "c1"], "x", 0, 0)] * 2
    calls = spark.createDataFrame(rows, "conv_id long, turn int, call_id string, name string, arguments string, depends_on array<string>, content string, place int, step int")
    results = spark.createDataFrame([(1, 60, "c0", "done", "f")], "conv_id long, turn int, call_id string, content string, name string")
    got = tool_calls.link(calls, results, schemas).collect()
    first = {r["call_id"]: r["first_error"] for r in got}
    for r in got:
        json.loads(r["json"])
        assert not {"NaN", "Infinity"} & set(r["json"].replace(":", ",").split(","))
    assert len(got) == len(rows)
    assert [first[f"c{i}"] for i in range(len(HOSTILE))] == [None, "$: not JSON", None, "$: not JSON", "$: not JSON", "$: not JSON", None, "$: not JSON", "$: not an object", None]
    assert first["c50"] == "$: not of type thing"
    assert {r["call_id"]: r["status"] for r in got}["c0"] == "linked"
