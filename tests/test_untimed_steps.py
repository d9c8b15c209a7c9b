"""Experiments time their searches one by one; what nobody times runs at the same time."""

import threading

from quotaknn.plans import workloads


def test_untimed_steps_meet():
    both = threading.Barrier(2, timeout=20)  # passes only where two steps run at the same time
    assert sorted(workloads.together(both.wait, both.wait)) == [0, 1]


def test_timed_searches_run_alone_and_in_order(spark, monkeypatch):
    running, most, order = [], [], []
    real = workloads.search

    def search(*args, **kw):
        if kw.get("retriever") != "exact":
            running.append(1)
            most.append(len(running))
            order.append(kw.get("policy", "cell"))
        try:
            return real(*args, **kw)
        finally:
            if kw.get("retriever") != "exact":
                running.pop()

    monkeypatch.setattr(workloads, "search", search)
    rows = workloads.by_m(spark, "/root/testdata/sf0.001", "V_EMB", (1,), 2, 3, 2, False, dict(list(workloads.POLICIES.items())[:2])).collect()
    assert [(r["m"], r["setting"]) for r in rows] == [(1, "cell_lsh"), (1, "per_attribute_lsh")]
    assert max(most) == 1 and order == ["cell", "per_attribute"]
