"""What a Python worker holds, in bytes that numpy reports: an executor's two workers and its heap share one limit."""

import sys
import tracemalloc

import numpy as np

from quotaknn.llm import common, minhash


def brute_pairs(rows, percent):
    """Pairs of one block, one at a time."""
    found = set()
    for x in rows:
        for y in rows:
            lists = [k for k in x[8] if k in y[8] and k < x[9]]
            if x[1] >= y[1] or x[3] == y[3] or lists or (x[5] != x[6] and x[0] == y[0]):
                continue
            least, most, both = min(x[2], y[2]), max(x[2], y[2]), x[2] + y[2]
            if 100 * least < percent * most or (100 + percent) * min(x[7], y[7]) < percent * both:
                continue
            a, b = (set(np.frombuffer(r[4], np.uint64).tolist()) for r in (x, y))
            share, some = min(1.0, percent * both / ((100 + percent) * most)), min(len(a), len(b))
            if len(a & b) < some * share - 6 * (some * share * (1 - share)) ** 0.5 - 1e-3:
                continue
            if most > minhash.WIDE or 100 * len(a & b) >= percent * (both - len(a & b)) - 1e-3:
                found.add((x[1], y[1]))
    return found


def block(n, i, j, seed=5):
    draw = np.random.default_rng(seed)
    common_ = draw.integers(0, 1 << 62, 260).astype(np.uint64)
    rows = []
    for k in range(n):
        s = np.unique(np.concatenate([common_[: draw.integers(200, 260)], draw.integers(0, 1 << 62, draw.integers(0, 80)).astype(np.uint64)]))
        size = len(s)
        keys = draw.choice(40, 3, replace=False).tolist() + [100]
        rows.append((int(draw.integers(i, j + 1)), k, size, int(draw.integers(0, n // 2)), s[: minhash.WIDE].tobytes(), i, j, size, keys, int(30)))
    return rows


def test_block_pairs_are_those_of_brute_force():
    for i, j in ((0, 0), (0, 1)):
        rows = block(150, i, j)
        a, b = minhash.block_pairs(rows, 80)
        assert set(zip(a.tolist(), b.tolist())) == brute_pairs(rows, 80)
        assert len(a) == len(set(zip(a.tolist(), b.tolist()))) > 0


def test_a_full_block_needs_little_memory():
    rows = block(2 * minhash.BLOCK, 0, 1)
    tracemalloc.start()
    minhash.block_pairs(rows, 80)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 80e6, peak


def test_tokenizer_tables_stay_small():
    pieces, m = common.Pieces(common.tokenizer_path("word_bpe_49k.json")), 100_000
    for k in range(11):
        own = np.arange(k * m, (k + 1) * m, dtype=np.uint64)
        pieces.add(common.hash_rows(own), common.hash_rows(own + np.uint64(1 << 40)), [np.array([7, 8, 9], "<u4")] * m, [b"some words"] * m)
    held = sum(v.nbytes for v in vars(pieces).values() if isinstance(v, np.ndarray))
    assert pieces.n == 11 * m and held < 100e6, held
    last = pieces.n - 1
    assert pieces.flat[pieces.begin[last] : pieces.begin[last] + pieces.size[last]].tolist() == [7, 8, 9]
    assert pieces.text[pieces.text_at[last] : pieces.text_at[last] + pieces.text_size[last]].tobytes() == b"some words"


def test_steps_without_tokens_free_the_tables():
    import pyarrow as pa

    run = common.encoder(common.tokenizer_path("word_bpe_49k.json"), 1)
    assert [x.tolist()[-1] for x in run(pa.array(["a text of words"]))] == [1]
    assert "_quotaknn_encoders" in sys.__dict__
    assert list(common.lean(lambda batches: iter(batches))([1, 2])) == [1, 2]
    assert "_quotaknn_encoders" not in sys.__dict__
    assert [x.tolist()[-1] for x in run(pa.array(["a text of words"]))] == [1]
