"""The cutting game: states, moves and their effect. All of it is driver-side and sized by the grid alone.

A move is (row, column, direction) of a corner. A rightward cut may start where a vertical boundary stands and no
horizontal one runs; a downward cut the other way round. A cut runs to the first boundary that crosses it, so each
cut splits one rectangle and M - 1 cuts give M regions. The frame of the map counts as boundary.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np

from cutlearn.config import GridTooCoarse
from cutlearn.plans.grid import prefix
from cutlearn.plans.layout import Layout, Rect

RIGHT, DOWN = 0, 1


class Cut(NamedTuple):
    i: int
    j: int
    direction: int


class Board:
    """Boundaries on the corners of a g by g grid, and the rectangles between them."""

    def __init__(self, g: int):
        self.g = g
        self.h = np.zeros((g + 1, g + 1), np.uint8)
        self.v = np.zeros((g + 1, g + 1), np.uint8)
        self.h[0, :g] = self.h[g, :g] = 1
        self.v[:g, 0] = self.v[:g, g] = 1
        self.rects = [Rect(0, g, 0, g)]
        self.owner = np.zeros((g, g), np.int64)

    @property
    def layout(self) -> Layout:
        return Layout(tuple(self.rects), self.g)

    def mask(self) -> np.ndarray:
        """Which of the g * g * 2 actions may be taken."""
        h, v = self.h[: self.g, : self.g] == 1, self.v[: self.g, : self.g] == 1
        return np.stack([~h & v, h & ~v], axis=2).ravel()

    def action_id(self, cut: Cut) -> int:
        return (cut.i * self.g + cut.j) * 2 + cut.direction

    def cut_of(self, action: int) -> Cut:
        return Cut(action // 2 // self.g, action // 2 % self.g, action % 2)

    def step(self, action: int) -> Rect:
        """Draws the line of a valid action; returns the rectangle that it split."""
        cut = self.cut_of(action)
        k = int(self.owner[cut.i, cut.j])
        r = self.rects[k]
        if cut.direction == RIGHT:
            if not r.r0 < cut.i < r.r1 or cut.j != r.c0:
                raise ValueError(f"no cut starts there: {cut}")
            self.h[cut.i, r.c0 : r.c1] = 1
            a, b = r._replace(r1=cut.i), r._replace(r0=cut.i)
        else:
            if not r.c0 < cut.j < r.c1 or cut.i != r.r0:
                raise ValueError(f"no cut starts there: {cut}")
            self.v[r.r0 : r.r1, cut.j] = 1
            a, b = r._replace(c1=cut.j), r._replace(c0=cut.j)
        self.rects[k] = a
        self.rects.append(b)
        self.owner[b.r0 : b.r1, b.c0 : b.c1] = len(self.rects) - 1
        return r

    def copy(self) -> Board:
        other = Board.__new__(Board)
        other.g, other.rects = self.g, list(self.rects)
        other.h, other.v, other.owner = self.h.copy(), self.v.copy(), self.owner.copy()
        return other


class Encoder:
    """State vectors of boards over one histogram."""

    def __init__(self, hist: np.ndarray, mass_scale: str = "literal"):
        self.hist, self.sums, self.total = hist, prefix(hist), max(int(hist.sum()), 1)
        self.scale = 1.0 if mass_scale == "literal" else self.total / max(int(hist.max()), 1)

    def mass(self, board: Board) -> np.ndarray:
        """Share of the cell times share of its region, for each cell."""
        p = self.sums
        n = np.array([p[r.r1, r.c1] - p[r.r0, r.c1] - p[r.r1, r.c0] + p[r.r0, r.c0] for r in board.rects], float)
        return self.hist * n[board.owner] / self.total**2 * self.scale

    def __call__(self, board: Board) -> np.ndarray:
        out = np.zeros((3, board.g + 1, board.g + 1), np.float32)
        out[0], out[1] = board.h, board.v
        out[2, : board.g, : board.g] = self.mass(board)
        return out.ravel()


def replay(actions: list[int], g: int) -> Board:
    board = Board(g)
    for a in actions:
        board.step(a)
    return board


def check_moves(g: int, m: int) -> None:
    if m > g * g:
        raise GridTooCoarse(f"{m} regions from {g * g} cells")
