import numpy as np
import pytest

from entlink.joint import network as nw
from entlink.joint.train import Config, bags, fit_towers, load_tower, train, train_distributed


def test_hand_checked_values():
    assert nw.elu(np.array([-1.0, 2.0])) == pytest.approx([-0.632121, 2.0], abs=1e-6)
    assert nw.learning_rate(2500, 1e-5) == pytest.approx(8.1e-6)
    dist = np.array([[0.1, 0.3, 0.1, 0.25, 0.5]])
    match = np.array([[True, True, False, False, False]])
    assert nw.side_gradient(dist, match, 0.1)[0] == pytest.approx(0.25)
    assert nw.side_gradient(dist, match, 0.1, "each")[0] == pytest.approx(0.55)


@pytest.mark.parametrize("positive", ["mean", "each"])
def test_gradients_by_finite_differences(positive):
    rng = np.random.default_rng(0)
    gr, gt = nw.Tower((5, 7, 4), 1), nw.Tower((6, 4), 2)
    r, t, match = rng.normal(size=(6, 5)), rng.normal(size=(7, 6)), rng.random((6, 7)) < 0.3
    match[0] = [True, True, False, False, False, False, False]

    def value():
        return nw.loss_and_gradients(gr.forward(r), gt.forward(t), match, 0.3, positive)[0]

    _, dx, dy = nw.loss_and_gradients(gr.forward(r, rng), gt.forward(t, rng), match, 0.3, positive)
    for tower, grads in ((gr, gr.backward(dx)), (gt, gt.backward(dy))):
        for p, g in zip(tower.parameters(), grads):
            flat, own = p.reshape(-1), g.reshape(-1)
            for i in range(0, len(flat), max(1, len(flat) // 9)):
                keep, eps = flat[i], 1e-6
                flat[i] = keep + eps
                up = value()
                flat[i] = keep - eps
                down = value()
                flat[i] = keep
                assert own[i] == pytest.approx((up - down) / (2 * eps), abs=1e-5)


def test_loss_invariants():
    rng = np.random.default_rng(1)
    x, y, match = rng.normal(size=(5, 3)), rng.normal(size=(5, 3)), np.eye(5, dtype=bool)
    a = nw.loss_and_gradients(x, y, match, 0.2)[0]
    assert a >= 0
    assert nw.loss_and_gradients(y, x, match.T, 0.2)[0] == pytest.approx(a)
    assert nw.loss_and_gradients(x, y, match, 0.2, "each")[0] == pytest.approx(a)
    p = rng.permutation(5)
    assert nw.loss_and_gradients(x[p], y[p], match, 0.2)[0] == pytest.approx(a)
    assert nw.loss_and_gradients(np.eye(3), np.eye(3), np.eye(3, dtype=bool), 0.2)[0] == 0


def test_skew_sampler_flattens_counts():
    popularity = 1 / np.arange(1, 201)
    skew, uniform = nw.SkewSampler(200, seed=1), nw.UniformSampler(200, seed=1)
    for _ in range(300):
        skew.draw(10, popularity)
        uniform.draw(10, popularity)
    assert skew.seen.std() < uniform.seen.std()


def data():
    names = [f"{a} {b}" for a in ("red", "blue", "old", "new") for b in ("ring", "rod", "gear", "plate")]
    tuples = [(i, n, f"{n} size {i}") for i, n in enumerate(names)]
    mentions = [(i * 10 + j, n, f"somebody {v} the {n} today") for i, n in enumerate(names) for j, v in enumerate(("saw", "sold", "lost"))]
    return tuples, mentions


def test_training_separates_matches():
    tuples, mentions = data()
    c = Config(steps=120, checkpoints=(0,), batch=24)
    r, t = bags([x[2] for x in tuples], c.dim), bags([x[2] for x in mentions], c.dim)
    code = {n: i for i, (_, n, _) in enumerate(tuples)}
    ti = np.array([code[n] for _, n, _ in mentions])
    pairs = np.array([(i, j) for j, i in enumerate(ti)])

    def gap(gr, gt):
        (x, _), (y, _) = nw.unit_rows(gr.forward(r)), nw.unit_rows(gt.forward(t))
        d, same = 1 - x @ y.T, np.arange(len(r))[:, None] == ti[None]
        return d[~same].mean() - d[same].mean(), np.mean([same[i, d[i].argmin()] for i in range(len(r))])

    gaps = [gap(gr, gt) for _, gr, gt, _, _ in fit_towers(r, t, pairs, np.arange(len(r)), ti, c)]
    assert gaps[1][0] > gaps[0][0] + 0.1 and gaps[1][1] > 0.9


def test_weight_table_round_trip_and_distributed_steps(spark):
    tuples, mentions = data()
    c = Config(steps=5, dim=64, relation=(16, 8), text=(8,))
    vec = lambda s: bags([s], 64)[0].tolist()
    t = spark.createDataFrame([("x", str(i), n, vec(s)) for i, n, s in tuples], "entity_type string, tuple_id string, instance_id string, vec array<double>")
    m = spark.createDataFrame([("x", str(i), n, vec(s)) for i, n, s in mentions], "entity_type string, mention_id string, instance_id string, vec array<double>")
    w = train(t, m, c)
    assert load_tower(w, "x", "relation", 5).forward(np.ones((2, 64))).shape == (2, 8)
    by = {n: s for _, n, s in tuples}
    rows = [(bags([by[n]], 64)[0].tolist(), bags([s], 64)[0].tolist(), n) for _, n, s in mentions]
    frame = spark.createDataFrame(rows, "r_vec array<double>, t_vec array<double>, instance_id string").repartition(3)
    _, losses = train_distributed(frame, c, 6)
    assert losses[-1] < losses[0]


def test_registry_swaps_versions(spark, tmp_path):
    from entlink.joint.registry import ModelRegistry

    r = ModelRegistry(spark, str(tmp_path))
    assert r.current("m") is None
    assert r.publish("m", spark.range(3)) == 1
    assert r.publish("m", spark.range(5)) == 2
    assert r.load("m").count() == 5 and r.load("m", 1).count() == 3


def test_convolution_tower_gradients():
    rng = np.random.default_rng(4)
    g, x = nw.ConvTower(10, 4, 2, 3, 5, seed=1), rng.normal(size=(6, 10))
    goal = rng.normal(size=(6, 5))
    out = g.forward(x, rng)
    grads = g.backward(out - goal)
    for p, own in zip(g.parameters(), grads):
        flat, got = p.reshape(-1), own.reshape(-1)
        for i in range(0, len(flat), 5):
            keep = flat[i]
            flat[i] = keep + 1e-6
            up = ((g.forward(x) - goal) ** 2).sum() / 2
            flat[i] = keep - 1e-6
            down = ((g.forward(x) - goal) ** 2).sum() / 2
            flat[i] = keep
            assert got[i] == pytest.approx((up - down) / 2e-6, abs=1e-5)
