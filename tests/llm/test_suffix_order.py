"""Ranks of cover samples and repeats read off neighbours, against brute force."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pytest

from relayout.llm import suffix_dedup, suffix_order
from relayout.llm.repeats import Search
from relayout.llm.suffix_order import Shape, distinct_rows, shared_offsets
from tests.llm.test_repeats import brute_bytes, corpus, frame


@pytest.mark.parametrize(("window", "cover"), [(400, 7), (200, 7), (40, 3), (25, 3), (100, 2)])
def test_blocks_and_rest_fill_a_window(window, cover):
    shape = Shape.of(Search(False, window, 5, False, cover))
    assert shape.rest + shape.v * shape.depth == window and shape.v - 1 <= shape.rest < 2 * shape.v
    have = 1
    for behind in shape.rounds():
        assert behind <= have
        have += behind
    assert have == shape.depth


def test_windows_too_short_for_the_cover_are_refused():
    with pytest.raises(ValueError, match="cover"):
        Shape.of(Search(False, 100, 9, False, 7))


@pytest.mark.parametrize("seed", range(4))
def test_offsets_against_all_pairs(seed):
    draw = np.random.default_rng(seed)
    shape = Shape(9, 3, 2)
    n = 60
    rows = np.zeros((n, 15), np.uint8)
    rows[:, 7] = draw.integers(0, 5, n)
    n_left, n_right = draw.choice([2, 2, 2, 1, 0], n), draw.choice([3, 3, 3, 2, 1, 0], n)
    for k, (a, b) in enumerate(zip(n_left, n_right, strict=True)):
        rows[k, 8 : 8 + a], rows[k, 10 : 10 + b] = draw.integers(0, 3, a), draw.integers(0, 2, b)
    rows[:, 13], rows[:, 14] = n_left, n_right
    found, at, count = distinct_rows(rows)
    got = shared_offsets(shape, found, count)[at]
    for i, a in enumerate(rows):
        want = 0
        for x in range(3):
            like = lambda r: r[13] >= x and r[14] >= 3 - x  # noqa: B023, E731
            same = lambda r: like(r) and (r[:8] == a[:8]).all() and (r[8 : 8 + x] == a[8 : 8 + x]).all() and (r[10 : 13 - x] == a[10 : 13 - x]).all()  # noqa: B023, E731
            if like(a) and any(same(r) for j, r in enumerate(rows) if j != i):
                want |= 1 << x
        assert int(got[i]) == want


def test_ranks_follow_buckets_then_bytes():
    keys = np.array([[3, 1], [0, 9], [3, 0], [0, 9]], np.uint8)
    frame_ = pd.DataFrame({"part": [5, 8], "body": [keys[:2].tobytes(), keys[2:].tobytes()]})
    got = suffix_order.ranked(2)((np.int32(4),), frame_)
    ranks = [np.frombuffer(x, "<u8").tolist() for x in got["body"]]
    assert ranks == [[(4 << 32) | 2, 4 << 32], [(4 << 32) | 1, 4 << 32]] and got["part"].tolist() == [5, 8]


@pytest.mark.parametrize("width", [13, 16])
def test_wrong_ranks_give_wrong_results(spark, monkeypatch, width):
    """Both rounds matter: blocks of 13 bytes, and pairs of ranks."""
    right = suffix_order.ranked

    def wrong(w):
        answer = right(w)

        def run(key, frame):
            out = answer(key, frame)
            if w == width:  # equal keys of two parts get two ranks
                out["body"] = [(np.frombuffer(x, "<u8") + np.uint64((k + 1) << 50)).tobytes() for k, x in enumerate(out["body"])]
            return out

        return run

    # documents of several parts share a passage that no context settles
    draw = np.random.default_rng(3)
    word = lambda k: "".join(chr(97 + c) for c in draw.integers(0, 26, k))
    shared = word(300)
    rows = [(k, word(500) + shared + word(500)) for k in range(8)]
    docs = frame(spark, rows)
    assert sorted(map(tuple, suffix_dedup.digest(docs, size=40, gram=9, cover=3).collect()), key=str) == brute_bytes(rows, 40)
    monkeypatch.setattr(suffix_order, "ranked", wrong)
    assert sorted(map(tuple, suffix_dedup.digest(docs, size=40, gram=9, cover=3).collect()), key=str) != brute_bytes(rows, 40)


def test_shared_edges_with_another_middle_stay(spark):
    """Equal ends and a middle that each shares with a third text: only whole windows count."""
    left, right, one, two = "L" * 5 + "abcdefghij", "klmnopqrst" + "R" * 5, "0123456789" * 3, "9876543210" * 3
    rows = [(1, left + one + right), (2, left + two + right), (3, "x" + one + "y"), (4, "z" + two + "w"), *corpus(9, 15)[1:]]
    rows = [(k, t) for k, (_, t) in enumerate(rows)]
    got = suffix_dedup.digest(frame(spark, rows), size=40, gram=9, cover=3)
    assert sorted(map(tuple, got.collect()), key=str) == brute_bytes(rows, 40)
