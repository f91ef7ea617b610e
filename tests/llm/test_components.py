"""Components joined by one task are those of the rounds."""

import pytest

from momenttree.llm import components as K


@pytest.mark.parametrize("in_task", [0, 3, 1_000])
def test_components(spark, monkeypatch, in_task):
    links = [(f"c{k:03}", f"c{k + 1:03}") for k in range(60)] + [("s", f"t{k}") for k in range(30)] + [("x", "y"), ("y", "x"), ("z", "z"), (None, "x")]
    rounds = []
    monkeypatch.setattr(K, "_renaming", lambda links, no, own=K._renaming: rounds.append(no) or own(links, no))
    got = {r.id: r.component for r in K.components(spark.createDataFrame(links, "a string, b string"), in_task).collect()}
    assert got == {f"c{k:03}": "c000" for k in range(61)} | {f"t{k}": "s" for k in range(30)} | {"s": "s", "x": "x", "y": "x", "z": "z"}
    assert (len(rounds) == 0) == (in_task == 1_000)
