"""Two prioritised memories: one of demonstrations, one of the agent's own episodes."""

from __future__ import annotations

from typing import NamedTuple

import numpy as np

from cutlearn.learning.qnet import Batch


class Transition(NamedTuple):
    state: np.ndarray
    action: int
    ret: float
    steps: int
    state2: np.ndarray
    done: bool
    mask: np.ndarray
    mask2: np.ndarray


def n_step(states: list[np.ndarray], masks: list[np.ndarray], actions: list[int], rewards: list[float], n: int, discount: float) -> list[Transition]:
    """states and masks have one more entry than actions. A tail shorter than n ends the episode."""
    out = []
    for t, action in enumerate(actions):
        z = min(t + n, len(actions))
        ret = sum(discount**k * r for k, r in enumerate(rewards[t:z]))
        out.append(Transition(states[t], action, ret, z - t, states[z], z == len(actions), masks[t], masks[z]))
    return out


class SumTree:
    """Sums of priorities in a binary tree: sampling and updating take log(capacity)."""

    def __init__(self, cap: int):
        self.size = 1 << max(0, (cap - 1).bit_length())
        self.tree = np.zeros(2 * self.size)

    def set(self, k: int, value: float) -> None:
        k += self.size
        self.tree[k] = value
        while k > 1:
            k //= 2
            self.tree[k] = self.tree[2 * k] + self.tree[2 * k + 1]

    def find(self, mass: float) -> int:
        k = 1
        while k < self.size:
            k *= 2
            if mass >= self.tree[k] and self.tree[k + 1] > 0:
                mass -= self.tree[k]
                k += 1
        return k - self.size

    @property
    def total(self) -> float:
        return float(self.tree[1])


class Memory:
    """Keeps the first `pinned` entries for good; later ones make room oldest first."""

    def __init__(self, cap: int, alpha: float, floor: float):
        self.cap, self.alpha, self.floor = cap, alpha, floor
        self.items: list[Transition] = []
        self.times: list[tuple[float, ...] | None] = []
        self.tree, self.top, self.pinned, self.next = SumTree(cap), 1.0, 0, 0

    def add(self, t: Transition, times: tuple[float, ...] | None = None) -> None:
        """times: seconds of the episode's queries, if its reward may be worked out again."""
        if len(self.items) < self.cap:
            k = len(self.items)
            self.items.append(t)
            self.times.append(times)
        else:
            k = self.next = max(self.next, self.pinned)
            if k >= self.cap:
                k = self.next = self.pinned
            if k >= self.cap:
                return
            self.items[k], self.times[k] = t, times
            self.next += 1
        self.tree.set(k, self.top)

    def reprice(self, reward_of, discount: float) -> None:
        """Returns from the kept times and today's reward. Only the end of an episode is rewarded, so only steps that
        reach it change."""
        for k, (t, times) in enumerate(zip(self.items, self.times, strict=True)):
            if times is not None and t.done:
                self.items[k] = t._replace(ret=discount ** (t.steps - 1) * reward_of(times))

    def sample(self, n: int, rng: np.random.Generator) -> list[int]:
        return [min(self.tree.find(u), len(self.items) - 1) for u in rng.uniform(0, self.tree.total, n)] if self.items else []

    def chance(self, k: int) -> float:
        return self.tree.tree[self.tree.size + k] / self.tree.total

    def refresh(self, k: int, error: float) -> None:
        p = (abs(error) + self.floor) ** self.alpha
        self.top = max(self.top, p)
        self.tree.set(k, p)


class DualMemory:
    def __init__(self, cfg):
        self.cfg = cfg
        self.demo = Memory(cfg.demo_cap, cfg.alpha, cfg.priority_floor)
        self.agent = Memory(cfg.agent_cap, cfg.alpha, cfg.priority_floor)

    def route(self, transitions: list[Transition], reward: float, times: tuple[float, ...] | None = None) -> str:
        """An episode better than the best goes to the demonstrations, any other to the agent's memory."""
        name = "demo" if reward > 1 else "agent"
        for t in transitions:
            getattr(self, name).add(t, times)
        return name

    def reprice(self, reward_of) -> None:
        for memory in (self.demo, self.agent):
            memory.reprice(reward_of, self.cfg.discount)

    def sample(self, rng: np.random.Generator, demo_only: bool = False) -> tuple[Batch, list[tuple[Memory, int]]]:
        """rho of a batch comes from the demonstrations, and what the agent's memory can't give yet."""
        want = 0 if demo_only else round(self.cfg.batch * (1 - self.cfg.rho))
        own = want if len(self.agent.items) >= want or not self.demo.items else 0
        shares = [(self.demo, self.cfg.batch - own if self.demo.items else 0), (self.agent, own if self.demo.items else self.cfg.batch)]
        rows, places, weights = [], [], []
        for memory, n in shares:
            for k in memory.sample(n, rng):
                rows.append(memory.items[k])
                places.append((memory, k))
                weights.append((len(memory.items) * memory.chance(k)) ** -self.cfg.beta)
        w = np.array(weights) / max(weights)
        cols = [np.array(c) for c in zip(*rows, strict=True)]
        return Batch(*cols, np.array([m is self.demo for m, _ in places]), w), places

    def refresh(self, places: list[tuple[Memory, int]], errors: np.ndarray) -> None:
        for (memory, k), e in zip(places, errors, strict=True):
            memory.refresh(k, float(e))
