"""Components of few links come from one task, and are those of the rounds."""

import numpy as np
import pytest

from rankgrid.llm import components


@pytest.mark.parametrize("case", ["path", "random", "star", "loops", "none"])
def test_few_links_need_no_rounds(spark, monkeypatch, case):
    rng = np.random.default_rng(5)
    rows = {
        "path": [(k * 7 % 101, (k + 1) * 7 % 101) for k in range(100)],
        "random": [tuple(map(int, p)) for p in rng.integers(-500, 500, (300, 2))],
        "star": [(50, k) for k in range(100)] + [(1 << 60, (1 << 60) + 1)],
        "loops": [(3, 3), (4, 4)],
        "none": [],
    }[case]
    links = spark.createDataFrame(rows, "a long, b long")
    with monkeypatch.context() as m:
        m.setattr(components, "left_join", None)
        got = components.components(links)
        assert got.columns == ["node", "component"]
        got = sorted(map(tuple, got.collect()))
    parent = {}

    def root(k):
        while parent.setdefault(k, k) != k:
            k = parent[k]
        return k

    for a, b in rows:
        x, y = root(a), root(b)
        parent[max(x, y)] = min(x, y)
    assert got == sorted((k, root(k)) for k in list(parent) if root(k) != k)
    if case in ("path", "random"):
        monkeypatch.setattr(components, "FEW", 0)
        assert sorted(map(tuple, components.components(links).collect())) == got
