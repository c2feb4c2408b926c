"""The game: worked example, valid moves, state."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from cutlearn.config import GridTooCoarse, InvalidLayout
from cutlearn.learning.env import DOWN, RIGHT, Board, Cut, Encoder, check_moves, replay
from cutlearn.plans.demo import cut_order
from cutlearn.plans.grid import GridSpec
from cutlearn.plans.layout import Layout, Rect


def test_worked_example():
    board, hist = Board(6), np.ones((6, 6), np.int64)
    encode = Encoder(hist)
    board.step(board.action_id(Cut(0, 3, DOWN)))
    before = encode.mass(board)[2, 3]
    board.step(board.action_id(Cut(2, 3, RIGHT)))
    assert board.layout.key == (Rect(0, 2, 3, 6), Rect(0, 6, 0, 3), Rect(2, 6, 3, 6))
    assert board.h[2, 3] == 1 and board.v[2, 3] == 1
    assert encode.mass(board)[2, 3] < before


def test_published_sizes():
    spec = GridSpec(0, 0, 9, 9, 30)
    assert (spec.state_dim, spec.actions, Board(30).mask().sum()) == (2883, 1800, 58)


@settings(max_examples=60, deadline=None)
@given(st.integers(3, 9), st.integers(0, 10_000))
def test_moves_are_the_interior_lines_of_rectangles(g, seed):
    rng, board = np.random.default_rng(seed), Board(g)
    for k in range(10):
        valid = np.flatnonzero(board.mask())
        assert len(valid) == sum(r.r1 - r.r0 + r.c1 - r.c0 - 2 for r in board.rects)
        assert len(board.rects) == k + 1
        board.layout.validate()
        assert (board.layout.lookup == board.owner).all()
        if not len(valid):
            break
        board.step(int(rng.choice(valid)))
    assert replay(list(cut_order(board.layout)), g).layout.key == board.layout.key


def test_invalid_moves_raise():
    board = Board(4)
    for cut in (Cut(0, 0, DOWN), Cut(0, 0, RIGHT), Cut(2, 2, RIGHT)):
        assert not board.mask()[board.action_id(cut)]
        with pytest.raises(ValueError):
            board.step(board.action_id(cut))


def test_mass_sums_and_scale():
    hist = np.arange(16).reshape(4, 4)
    board = Board(4)
    assert Encoder(hist).mass(board).sum() == pytest.approx(1)
    board.step(board.action_id(Cut(0, 2, DOWN)))
    n = board.layout.counts(hist)
    assert Encoder(hist).mass(board).sum() == pytest.approx((n**2).sum() / hist.sum() ** 2)
    assert Encoder(hist, "unit").mass(Board(4)).max() == pytest.approx(1)


def test_pinwheel_is_no_cut_sequence():
    pinwheel = Layout((Rect(0, 1, 0, 2), Rect(0, 2, 2, 3), Rect(2, 3, 1, 3), Rect(1, 3, 0, 1), Rect(1, 2, 1, 2)), 3).validate()
    with pytest.raises(InvalidLayout):
        cut_order(pinwheel)


def test_bad_layouts_and_counts():
    with pytest.raises(InvalidLayout):
        Layout((Rect(0, 2, 0, 4),), 4).validate()
    with pytest.raises(InvalidLayout):
        Layout((Rect(0, 4, 0, 4), Rect(0, 0, 0, 4)), 4).validate()
    with pytest.raises(GridTooCoarse):
        check_moves(2, 5)
    assert Layout.from_json(Layout.whole(3).to_json()).key == Layout.whole(3).key
