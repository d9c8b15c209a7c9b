import os
import uuid

import numpy as np
from quotaknn.llm import ann, common


def test_matches_of_a_piece_are_those_of_its_trees():
    """All trees together, against one tree at a time: places, prefix lengths and what comes first."""
    rng = np.random.default_rng(3)
    x = rng.standard_normal((700, 12))
    x[:90] = x[0] + 1e-6 * rng.standard_normal((90, 12))  # matches longer than the heads that are looked up
    hashes = ann.Hashes(12, float(np.sqrt((x**2).sum(1).max())))
    trees, asked = ann.Trees(hashes, x), hashes.codes(x[:60:5], True)
    for enough in (40, 900, 5_000):
        reach, lo, hi = trees.ascend(asked, enough)
        for i, code in enumerate(asked):
            sizes = [sum(int(b[0, 0] - a[0, 0]) for a, b in (ann.ranges(s, code[t : t + 1], [y]) for t, s in enumerate(trees.strings))) for y in range(ann.BITS + 1)]
            assert reach[i] == max(y for y in range(ann.BITS + 1) if sizes[y] >= enough)
            nodes, bits = [], []
            for t, s in enumerate(trees.strings):
                a, b = ann.ranges(s, code[t : t + 1], range(reach[i], ann.BITS + 1))
                nodes.append(trees.order[t, a[0, 0] : b[0, 0]])
                bits.append(ann.matched(a[:, 0], b[:, 0], int(reach[i])))
            got = trees.matches(code, lo[i], hi[i])
            assert (got[0] == np.concatenate(nodes)).all() and (got[1] == np.concatenate(bits)).all()
            for scored in (5, 60, 2_000):
                assert sorted(trees.first(code, lo[i], hi[i], scored)) == sorted(ann.ranked(*got)[:scored])


def test_no_strings_or_matches_are_written(spark, tmp_path, monkeypatch):
    """What a search leaves in the shared folder are the vectors once and narrow tables, far below 128 strings a vector."""
    monkeypatch.setattr(common, "scratch", lambda spark, name: f"file://{tmp_path}/{name}-{uuid.uuid4().hex}")
    rng = np.random.default_rng(5)
    n, dim = 9_000, 8
    table = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.standard_normal((n, dim)))], "vec_id long, embedding array<double>")
    assert ann.search(table).count() == n // 20 * 20
    assert sum(os.path.getsize(os.path.join(at, f)) for at, _, files in os.walk(tmp_path) for f in files) < 4 * n * dim * 8
