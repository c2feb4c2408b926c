"""Choosing actions, pre-training on a demonstration and training against a cost."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np

from cutlearn.config import TrainConfig, Workload
from cutlearn.learning.env import DOWN, Board, Encoder, check_moves
from cutlearn.learning.memory import DualMemory, Transition, n_step
from cutlearn.learning.qnet import QNet, learn
from cutlearn.plans.cost import reward, workload_time
from cutlearn.plans.demo import Demo
from cutlearn.plans.layout import Layout


def greedy(net: QNet, board: Board, encode: Encoder) -> int:
    """Best valid action; the lowest id of equally good ones."""
    return int(np.where(board.mask(), net.forward(encode(board))[0], -np.inf).argmax())


def shifted(board: Board, action: int, kind: str, rng: np.random.Generator) -> int:
    """A cut one cell beside the action's, at random; the action itself if there is none."""
    cut, mask = board.cut_of(action), board.mask()
    if kind == "perpendicular":
        near = [cut._replace(j=cut.j + s) if cut.direction == DOWN else cut._replace(i=cut.i + s) for s in (-1, 1)]
        near = [c for c in near if 0 <= c.i < board.g and 0 <= c.j < board.g and board.owner[c.i, c.j] == board.owner[cut.i, cut.j]]
    elif kind == "neighbour":
        near = [cut._replace(i=cut.i + a, j=cut.j + b) for a in (-1, 0, 1) for b in (-1, 0, 1) if (a, b) != (0, 0) and 0 <= cut.i + a < board.g and 0 <= cut.j + b < board.g]
    else:
        raise ValueError(kind)
    ids = [k for k in map(board.action_id, near) if mask[k]]
    return int(rng.choice(ids)) if ids else action


def choose(net: QNet, board: Board, encode: Encoder, cfg: TrainConfig, rng: np.random.Generator, base: int | None = None) -> int:
    """base: the action to shift instead of the network's best one, where it is valid."""
    eps_shift = cfg.eps_shift if cfg.grid_shift else 0.0
    u = rng.random()
    if u < cfg.eps_random:
        return int(rng.choice(np.flatnonzero(board.mask())))
    best = greedy(net, board, encode)
    share = (1 - cfg.eps_random) * eps_shift if cfg.shift_given_greedy else eps_shift
    if u >= cfg.eps_random + share:
        return best
    return shifted(board, best if base is None or not board.mask()[base] else base, cfg.shift, rng)


def greedy_layout(net: QNet, encode: Encoder, m: int) -> Layout:
    board = Board(len(encode.hist))
    for _ in range(m - 1):
        board.step(greedy(net, board, encode))
    return board.layout


def transitions(actions, encode: Encoder, last_reward: float, cfg: TrainConfig) -> list[Transition]:
    board = Board(len(encode.hist))
    states, masks = [encode(board)], [board.mask()]
    for a in actions:
        board.step(a)
        states.append(encode(board))
        masks.append(board.mask())
    rewards = [0.0] * (len(actions) - 1) + [last_reward]
    return n_step(states, masks, list(actions), rewards, cfg.n_step, cfg.discount)


@dataclass
class PretrainReport:
    iters: int
    converged: bool


@dataclass
class Episode:
    episode: int
    layout: Layout
    reward: float
    times: tuple[float, ...]
    stopped: bool
    cost: float
    best_cost: float
    wall: float


@dataclass
class TrainResult:
    best: Layout
    best_times: tuple[float, ...]
    demo_times: tuple[float, ...]
    pretrain: PretrainReport | None
    history: list[Episode] = field(default_factory=list)
    wall: float = 0.0

    @property
    def episodes(self) -> int:
        return len(self.history)


class Learner:
    def __init__(self, hist: np.ndarray, m: int, cfg: TrainConfig):
        check_moves(len(hist), m)
        g = len(hist)
        self.cfg, self.m, self.encode = cfg, m, Encoder(hist, cfg.mass_scale)
        sizes = ((g + 1) ** 2 * 3, *cfg.hidden, g * g * 2)
        self.online, self.target = QNet(sizes, cfg.seed), QNet(sizes, cfg.seed)
        self.rng, self.memory, self.updates = np.random.default_rng(cfg.seed), DualMemory(cfg), 0

    def _update(self, demo_only: bool = False) -> dict[str, float]:
        batch, places = self.memory.sample(self.rng, demo_only)
        losses, errors = learn(self.online, self.target, batch, self.cfg)
        self.memory.refresh(places, errors)
        self.updates += 1
        if self.updates % self.cfg.target_every == 0:
            self.target.copy_from(self.online)
        return losses

    def _reprice(self, best_times: tuple[float, ...], workload: Workload) -> None:
        if self.cfg.renormalise_rewards:
            self.memory.reprice(lambda times: reward(best_times, times, workload.freqs, self.cfg.reward_kind))

    def pretrain(self, demo: Demo) -> PretrainReport:
        """Only the demonstration is learned from, until a greedy episode rebuilds its layout."""
        for k in range(self.cfg.pretrain_iters):
            self._update(demo_only=True)
            if greedy_layout(self.online, self.encode, self.m).key == demo.layout.key:
                return PretrainReport(k + 1, True)
        return PretrainReport(self.cfg.pretrain_iters, False)

    def train(self, demo: Demo, workload: Workload, cost) -> TrainResult:
        cfg, began = self.cfg, time.monotonic()
        if cfg.shift_base not in ("model", "best_layout"):
            raise ValueError(cfg.shift_base)
        demo_times = cost.evaluate(demo.layout, workload).times
        for t in transitions(demo.actions, self.encode, 1.0, cfg):
            self.memory.demo.add(t, demo_times)
        self.memory.demo.pinned = len(self.memory.demo.items)
        result = TrainResult(demo.layout, demo_times, demo_times, None)
        if cfg.pretrain:
            result.pretrain = self.pretrain(demo)
            self.updates = 0
        first, best_actions = not cfg.pretrain, list(demo.actions) if cfg.pretrain else []
        best_cost = workload_time(demo_times, workload.freqs)
        for e in range(cfg.episodes):
            if time.monotonic() - began > cfg.wall_cap_s:
                break
            board, actions = Board(len(self.encode.hist)), []
            if cfg.refresh_best_every and e and e % cfg.refresh_best_every == 0:
                cost.forget(result.best)
                result.best_times = cost.evaluate(result.best, workload).times
                self._reprice(result.best_times, workload)
            for t in range(self.m - 1):
                base = best_actions[t] if cfg.shift_base == "best_layout" and best_actions else None
                actions.append(choose(self.online, board, self.encode, cfg, self.rng, base))
                board.step(actions[-1])
                if t < self.m - 2:
                    self._update()
            got = cost.evaluate(board.layout, workload, None if first else result.best_times, cfg)
            if first:  # without a demonstration the first episode is what later ones are held against
                result.best, result.best_times, best_actions, first = board.layout, got.times, actions, False
                best_cost = workload_time(got.times, workload.freqs)
            r = cfg.stop_reward if got.stopped else reward(result.best_times, got.times, workload.freqs, cfg.reward_kind)
            self.memory.route(transitions(actions, self.encode, r, cfg), r, None if got.stopped else got.times)
            if r > 1:
                result.best, result.best_times, best_actions = board.layout, got.times, actions
                self._reprice(result.best_times, workload)
            paid = workload_time(got.times, workload.freqs)
            best_cost = min(best_cost, paid) if not got.stopped else best_cost
            result.history.append(Episode(e, board.layout, r, got.times, got.stopped, paid, best_cost, time.monotonic() - began))
            self._update()
        result.wall = time.monotonic() - began
        return result


def imitation_accuracy(net: QNet, encode: Encoder, demo: Demo) -> float:
    board, hits = Board(len(encode.hist)), 0
    for a in demo.actions:
        hits += greedy(net, board, encode) == a
        board.step(a)
    return hits / max(len(demo.actions), 1)
