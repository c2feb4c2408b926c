"""Losses, memories, agents and training."""

import copy
from dataclasses import replace

import numpy as np
import pytest

from cutlearn.config import BadWorkload, DistanceJoin, Environment, TrainConfig, Workload
from cutlearn.learning import qnet
from cutlearn.learning.env import DOWN, Board, Cut, Encoder
from cutlearn.learning.learner import Learner, choose, greedy_layout, imitation_accuracy, shifted, transitions
from cutlearn.learning.memory import DualMemory, Memory, SumTree, Transition, n_step
from cutlearn.learning.qnet import Batch, QNet, tabular_update
from cutlearn.plans.baselines import hist_kdb
from cutlearn.plans.cost import CostResult, ModelledCost, dp_optimum, reward, workload_time
from cutlearn.plans.demo import Demo, cut_order
from cutlearn.plans.grid import GridSpec


def batch(n=6, dim=5, actions=4, seed=0):
    rng = np.random.default_rng(seed)
    f = lambda *s: rng.normal(size=s)
    mask = np.ones((n, actions), bool)
    mask[:, 3] = False
    return Batch(f(n, dim), rng.integers(0, 3, n), f(n), np.full(n, 3), f(n, dim), np.arange(n) % 2 == 0, mask, mask, np.arange(n) < 3, rng.uniform(0.5, 1, n))


@pytest.mark.parametrize("kind", ["td", "margin"])
def test_gradients_match_differences(kind):
    b, net = batch(), QNet((5, 7, 4), 1)
    net.params = [p.astype(np.float64) for p in net.params]
    target = qnet.td_targets(b, net, net, 0.9)

    def loss():
        q = net.forward(b.state)
        return (qnet.td_loss(q, b, target) if kind == "td" else qnet.margin_loss(q, b, 0.8))[0]

    kept = []
    q = net.forward(b.state, kept)
    g = (qnet.td_loss(q, b, target) if kind == "td" else qnet.margin_loss(q, b, 0.8))[1]
    grads = net.backward(kept, g)
    for p, d in zip(net.params, grads, strict=True):
        for at in [tuple(0 for _ in p.shape), tuple(s - 1 for s in p.shape)]:
            old = p[at]
            p[at] = old + 1e-6
            up = loss()
            p[at] = old - 1e-6
            down = loss()
            p[at] = old
            assert d[at] == pytest.approx((up - down) / 2e-6, abs=1e-6)


def test_margin_loss_is_zero_only_with_a_lead():
    b = batch()._replace(demo=np.ones(6, bool))
    q = np.zeros((6, 4))
    q[np.arange(6), b.action] = 0.79
    assert qnet.margin_loss(q, b, 0.8)[0] == pytest.approx(0.01)
    q[np.arange(6), b.action] = 0.8
    assert qnet.margin_loss(q, b, 0.8)[0] == 0
    q[:, 3] = 100  # an invalid action doesn't count
    assert qnet.margin_loss(q, b, 0.8)[0] == 0
    assert qnet.margin_loss(np.zeros((6, 4)), b._replace(demo=np.zeros(6, bool)), 0.8)[0] == 0


def test_n_step_by_hand():
    states, masks = [np.array([k]) for k in range(8)], [np.ones(2, bool)] * 8
    ts = n_step(states, masks, list(range(7)), [0, 0, 0, 0, 0, 0, 2.0], 3, 0.5)
    assert [t.ret for t in ts] == [0, 0, 0, 0, 0.5, 1, 2]
    assert [t.done for t in ts] == [False] * 4 + [True] * 3
    assert [t.steps for t in ts] == [3, 3, 3, 3, 3, 2, 1] and [int(t.state2[0]) for t in ts] == [3, 4, 5, 6, 7, 7, 7]


def test_bootstrap_kinds():
    b, a, z = batch(), QNet((5, 4), 1), QNet((5, 4), 2)
    later, own = z.forward(b.state2)[:, :3], a.forward(b.state2)[:, :3]
    full = qnet.td_targets(b, a, z, 0.9)
    assert full[1] == pytest.approx(b.ret[1] + 0.9**3 * later[1].max(), rel=1e-5) and full[0] == b.ret[0]
    assert qnet.td_targets(b, a, z, 0.9, "double")[1] == pytest.approx(b.ret[1] + 0.9**3 * later[1][own[1].argmax()], rel=1e-5)
    assert qnet.td_targets(b, a, z, 0.9, discount_bootstrap=False)[1] == pytest.approx(b.ret[1] + later[1].max(), rel=1e-5)


def test_sum_tree_samples_by_priority():
    tree = SumTree(4)
    for k, p in enumerate((1.0, 0.0, 3.0, 4.0)):
        tree.set(k, p)
    rng = np.random.default_rng(0)
    got = np.bincount([tree.find(u) for u in rng.uniform(0, tree.total, 8000)], minlength=4) / 8000
    assert np.allclose(got, [1 / 8, 0, 3 / 8, 4 / 8], atol=0.02)


def step(k):
    return Transition(np.array([float(k)]), 0, 0.0, 1, np.array([0.0]), True, np.ones(1, bool), np.ones(1, bool))


def test_memories_pin_evict_route_and_share():
    m = Memory(4, 0.6, 1e-3)
    for k in range(2):
        m.add(step(k))
    m.pinned = 2
    for k in range(2, 9):
        m.add(step(k))
    assert [t.state[0] for t in m.items][:2] == [0, 1] and len(m.items) == 4
    d = DualMemory(TrainConfig())
    for _ in range(7):
        d.demo.add(step(0))
    b, _ = d.sample(np.random.default_rng(0))
    assert b.demo.all() and len(b.demo) == 32
    assert d.route([step(1)] * 30, 0.9) == "agent" and d.route([step(1)], 1.1) == "demo"
    b, places = d.sample(np.random.default_rng(0))
    assert b.demo.sum() == 8 and len(places) == 32
    assert d.sample(np.random.default_rng(0), True)[0].demo.all()


def test_rewards():
    f = (0.25, 0.5, 0.25)
    assert reward((1, 2, 3), (1, 2, 3), f) == pytest.approx(1)
    assert reward((1, 2, 3), (0.5, 2, 3), f) == pytest.approx(1.25**2)
    assert reward((2, 2), (1, 4), (0.5, 0.5)) > 1 > reward((2, 2), (1, 4), (0.5, 0.5), "ratio_of_means")
    with pytest.raises(BadWorkload):
        Workload((DistanceJoin(5, 0.5),))


def toy(g=4, m=3, seed=3, index=False):
    rng = np.random.default_rng(seed)
    fine = (rng.exponential(1, (g * 2, g * 2)) ** 2 * 20).astype(np.int64)
    spec = GridSpec(0, 0, 999, 999, g)
    hist = fine.reshape(g, 2, g, 2).sum(axis=(1, 3))
    layout = hist_kdb(hist, m)
    return fine, spec, hist, Demo(layout, cut_order(layout), "kdb"), ModelledCost(fine, spec, Environment(m, index), c_net=0.0)


def every_layout(g, m):
    seen, todo = {}, [Board(g)]
    for _ in range(m - 1):
        nxt = {}
        for b in todo:
            for a in np.flatnonzero(b.mask()):
                c = b.copy()
                c.step(int(a))
                nxt[c.layout.key] = c
        todo = list(nxt.values())
    seen = {b.layout.key: b.layout for b in todo}
    return list(seen.values())


def test_dp_equals_exhaustive_search():
    _, _, _, _, cost = toy()
    for objective in ("max", "sum"):
        one = lambda r: (lambda a, b, c: cost.c_row * (a + b) + cost.c_pair * c)(*cost.region(r, 50))
        pick = max if objective == "max" else sum
        best = min(pick([one(r) for r in l.rects]) for l in every_layout(4, 3))
        value, layout = dp_optimum(cost, 50, 3, objective)
        assert value == pytest.approx(best) and layout.validate() and pick([one(r) for r in layout.rects]) == pytest.approx(best)


def test_tabular_learning_finds_the_optimum():
    _, _, _, _, cost = toy()
    best = dp_optimum(cost, 50, 3)[0]
    rng, q = np.random.default_rng(0), {}
    for _ in range(4000):
        board, path = Board(4), []
        for _ in range(2):
            valid = np.flatnonzero(board.mask())
            key = board.layout.key
            a = int(rng.choice(valid)) if rng.random() < 0.4 else int(max(valid, key=lambda v: q.get((key, int(v)), 0)))
            board.step(a)
            path.append((key, a, board.layout.key, [int(v) for v in np.flatnonzero(board.mask())]))
        r = best / cost.query(board.layout, 50)
        for k, (s, a, s2, valid2) in enumerate(path):
            last = k == len(path) - 1
            tabular_update(q, s, a, r if last else 0.0, s2, [] if last else valid2, 0.5, 0.99)
    board = Board(4)
    for _ in range(2):
        board.step(int(max(np.flatnonzero(board.mask()), key=lambda v: q.get((board.layout.key, int(v)), 0))))
    assert cost.query(board.layout, 50) == pytest.approx(best)


SMALL = TrainConfig(g=4, hidden=(64, 32), episodes=300, pretrain_iters=800, target_every=20)


def test_toy_training_reaches_the_optimum():
    _, _, hist, demo, cost = toy()
    r = Learner(hist, 3, SMALL).train(demo, Workload((DistanceJoin(50, 1.0),)), cost)
    assert r.best_times[0] == pytest.approx(dp_optimum(cost, 50, 3)[0])
    assert r.pretrain.converged and r.episodes == 300


def test_pretraining_rebuilds_the_demonstration():
    _, _, hist, demo, _ = toy(8, 4)
    cfg = replace(SMALL, g=8)
    learner = Learner(hist, 4, cfg)
    for t in transitions(demo.actions, learner.encode, 1.0, cfg):
        learner.memory.demo.add(t)
    assert learner.pretrain(demo).converged
    assert greedy_layout(learner.online, learner.encode, 4).key == demo.layout.key
    assert imitation_accuracy(learner.online, learner.encode, demo) > 0


def test_never_worse_than_the_demonstration_by_weighted_time():
    _, _, hist, demo, cost = toy(6, 4, index=True)
    w = Workload(tuple(DistanceJoin(d, f) for d, f in ((20, 0.25), (50, 0.5), (90, 0.25))))
    r = Learner(hist, 4, replace(SMALL, g=6, episodes=80, reward_kind="ratio_of_means")).train(demo, w, cost)
    assert workload_time(r.best_times, w.freqs) <= workload_time(r.demo_times, w.freqs) * (1 + 1e-12)
    best = [e.best_cost for e in r.history]
    assert best == sorted(best, reverse=True)


def test_runs_repeat_and_arms_differ():
    _, _, hist, demo, cost = toy(6, 4)
    w = Workload((DistanceJoin(50, 1.0),))
    run = lambda **c: Learner(hist, 4, replace(SMALL, g=6, episodes=30, **c)).train(demo, w, copy.deepcopy(cost))
    assert [e.reward for e in run().history] == [e.reward for e in run().history]
    assert run(pretrain=False).pretrain is None
    assert not any(e.stopped for e in run(exec_stop=False).history)


def test_stop_gives_the_small_reward():
    class Slow:
        def evaluate(self, layout, workload, best=None, cfg=None):
            return CostResult((1.0,)) if best is None else CostResult((9.0,), True)

    _, _, hist, demo, _ = toy()
    r = Learner(hist, 3, replace(SMALL, episodes=5)).train(demo, Workload((DistanceJoin(5, 1.0),)), Slow())
    assert {e.reward for e in r.history} == {0.2} and r.best.key == demo.layout.key


def test_shift_moves_one_cell_in_the_same_rectangle():
    board, rng = Board(6), np.random.default_rng(0)
    a = board.action_id(Cut(0, 3, DOWN))
    assert {board.cut_of(shifted(board, a, "perpendicular", rng)) for _ in range(30)} == {Cut(0, 2, DOWN), Cut(0, 4, DOWN)}
    tiny = Board(2)
    only = tiny.action_id(Cut(0, 1, DOWN))
    assert shifted(tiny, only, "perpendicular", rng) == only
    net, enc = QNet((49 * 3, 8, 72), 0), Encoder(np.ones((6, 6), np.int64))
    picks = [choose(net, board, enc, TrainConfig(eps_random=0, eps_shift=0), rng) for _ in range(5)]
    assert len(set(picks)) == 1 and board.mask()[picks[0]]


def test_network_saves_and_loads(tmp_path):
    net = QNet((5, 4, 3), 0)
    net.save(str(tmp_path / "net.npz"))
    x = np.ones((1, 5))
    assert np.allclose(QNet.load(str(tmp_path / "net.npz")).forward(x), net.forward(x))


def test_shift_can_start_from_the_best_layout():
    board, cfg = Board(8), TrainConfig(g=8, hidden=(16,), eps_random=0.0, eps_shift=1.0)
    encode = Encoder(np.ones((8, 8)), "unit")
    net, rng = QNet((9 * 9 * 3, 16, 128), 0), np.random.default_rng(0)
    base = board.action_id(Cut(0, 4, DOWN))
    beside = {board.action_id(Cut(0, j, DOWN)) for j in (3, 5)}
    assert {choose(net, board, encode, cfg, rng, base) for _ in range(30)} == beside
    board.step(base)  # not valid any more: the network's own action is shifted
    assert all(board.mask()[choose(net, board, encode, cfg, rng, base)] for _ in range(30))


def test_rewards_follow_the_best_layout():
    cfg = TrainConfig(agent_cap=4, demo_cap=4, discount=0.5)
    memory = DualMemory(cfg)
    states, masks = [np.zeros(1)] * 5, [np.ones(2, bool)] * 5
    memory.route(n_step(states, masks, [0] * 4, [0, 0, 0, 1.0], 3, 0.5), 1.0, (4.0,))
    memory.reprice(lambda times: (2.0 / times[0]) ** 2)
    assert [t.ret for t in memory.agent.items] == [0, 0.0625, 0.125, 0.25]
    memory.route(n_step(states, masks, [0] * 4, [0, 0, 0, 0.2], 3, 0.5), 0.2)  # a stopped episode keeps its reward
    memory.reprice(lambda times: 9.0)
    assert [t.ret for t in memory.agent.items] == [0, 0.05, 0.1, 0.2]


@pytest.mark.parametrize("change", [{"shift_base": "best_layout"}, {"renormalise_rewards": True}, {"refresh_best_every": 5}])
def test_training_options_never_end_worse(change):
    _, _, hist, demo, cost = toy(8, 4)
    cfg = replace(SMALL, g=8, episodes=30, reward_kind="ratio_of_means", **change)
    w = Workload((DistanceJoin(50, 1.0),))
    got = Learner(hist, 4, cfg).train(demo, w, cost)
    assert got.episodes == 30 and workload_time(got.best_times, w.freqs) <= workload_time(got.demo_times, w.freqs)
    with pytest.raises(ValueError):
        Learner(hist, 4, replace(cfg, shift_base="x")).train(demo, w, cost)


def test_training_on_measured_seconds(spark):
    from cutlearn import experiments as ex

    got = ex.train_measured(spark, "/root/testdata/sf0.001", cfg=replace(ex.MEASURED, g=6, episodes=2), m=4).collect()
    assert [r.arm for r in got] == ["stop", "no_stop"]
    assert all(r.episodes == 2 and 0 < r.best_s and 0 < r.best_again_s and 0 < r.demo_again_s and r.layout.count("(") == 4 for r in got)
    assert got[1].stopped == 0


def test_measured_training_is_the_whole_training(spark, monkeypatch):
    """The query trains both arms by the published settings: all episodes, three runs of a join, the whole grid and network."""
    from cutlearn import catalog
    from cutlearn.learning.learner import TrainResult

    seen = []

    def train(self, demo, workload, cost):
        seen.append((self.cfg.episodes, cost.repeats, len(self.encode.hist), self.cfg.hidden, self.cfg.wall_cap_s, self.cfg.exec_stop))
        return TrainResult(demo.layout, (1.0,) * 3, (1.0,) * 3, None)

    monkeypatch.setattr(Learner, "train", train)
    got = catalog.QUERIES["train_measured"](spark, "/root/testdata/sf0.001").collect()
    assert seen == [(5000, 3, 30, (1200, 600), 120 * 3600.0, stop) for stop in (True, False)] and len(got) == 2
