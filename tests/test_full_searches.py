"""The full arms of workloads take all points as centres."""

from __future__ import annotations

from curvetree.workloads import experiments


class Recorder:
    def __init__(self):
        self.sizes = []

    def radius(self, name, structure, kernel, r, n, curve="hilbert", bucket=128, output=None):
        self.sizes.append((structure, n))
        return {}

    def knn(self, name, structure, k, n, curve="hilbert"):
        self.sizes.append((structure, n))
        return {}


def test_full_arms(monkeypatch):
    b = Recorder()
    experiments.w5(b)
    assert {n for _, n in b.sizes} == {None}
    b = Recorder()
    experiments.w11(b)
    assert {s for s, n in b.sizes if n is None} == {s for s, _ in b.sizes}
    for w in (experiments.w9, experiments.w10):
        seen = []
        monkeypatch.setattr(experiments, "_local_seconds", lambda b, name, s, c, r, n, seen=seen: seen.append((s, n)) or 1.0)
        rows = w(None)
        assert {s for s, n in seen if n is None} == {s for s, _ in seen} and {r["centres"] for r in rows} == {300, "all"}
