"""Gradients against finite differences, pooling, training and storage."""

import numpy as np
import pytest

from varlink.nets.bilstm import CharBiLstm, encode_bytes
from varlink.nets.mlp import SetNet
from varlink.nets.objectives import OBJECTIVES, pick_negatives
from varlink.nets.train import Packed, TrainConfig, load_model, save_model, should_stop, train, triplet_gradient


def check_gradient(net, anchors, positives, negatives, objective="xent"):
    loss, grad = triplet_gradient(net, anchors, positives, negatives, objective)
    rng = np.random.default_rng(0)
    assert np.isfinite(loss)
    for name, p in net.params.items():
        flat, g = p.reshape(-1), grad[name].reshape(-1)
        for i in rng.integers(0, flat.size, 6):
            keep = flat[i]
            flat[i] = keep + 1e-5
            up = triplet_gradient(net, anchors, positives, negatives, objective)[0]
            flat[i] = keep - 1e-5
            down = triplet_gradient(net, anchors, positives, negatives, objective)[0]
            flat[i] = keep
            assert g[i] == pytest.approx((up - down) / 2e-5, rel=2e-3, abs=2e-6), (name, i)


@pytest.mark.parametrize("objective", sorted(OBJECTIVES))
def test_mlp_gradient(objective):
    rng = np.random.default_rng(1)
    sets = lambda k: [rng.normal(size=(int(rng.integers(1, 6)), 4)) for _ in range(k)]
    check_gradient(SetNet(4, 6, 5, 3).init(3), sets(3), sets(3), sets(3), objective)


def test_bilstm_gradient():
    net = CharBiLstm(units=4, n_out=3, depth=2, char_dim=3).init(2)
    words = [["ab", "c", ""], ["longer word", "ü"], ["ab"]]
    check_gradient(net, words, [["x", "ab"], ["é1"], ["zz top"]], [["12"], ["3", "44"], ["q"]])


def test_padding_does_not_matter():
    net = CharBiLstm(units=5, n_out=4).init(1)
    alone = net.forward(*encode_bytes(["abc"]))
    padded = net.forward(*encode_bytes(["abc", "a much longer string"]))
    assert np.allclose(alone[0][0], padded[0][0]) and np.allclose(alone[1][0], padded[1][0])


def test_shapes_of_the_published_networks():
    net = SetNet().init()
    n = lambda p: sum(v.size for k, v in net.params.items() if k.startswith(p))
    assert n("h") == 32 * 300 + 300 + 2 * (300 * 300 + 300) and n("g") == 32 * 300 + 300 + 300 * 300 + 300 + 301
    h, g = net.embed_sets(np.ones((4, 32)), np.ones(4), np.array([0, 1]))
    assert h.shape == (2, 300) and (np.abs(h) < 1).all() and (g >= 0).all()
    assert (SetNet(use_g=False).init().forward_g(np.ones((3, 32))) == 0).all()


def toy(n=60, seed=0):
    """Variables that differ in scale and place; datasets of a variable differ in sample and unit."""
    rng = np.random.default_rng(seed)
    from varlink.functions.encoding import np_bits32

    inputs, variable = [], []
    for i in range(n):
        v = i % 6
        x = rng.normal(10.0**v, 10.0**v / 5, 40)
        inputs.append(np_bits32(x))
        variable.append(v)
    return Packed([str(i) for i in range(n)], inputs, variable)


def test_training_separates():
    data, net = toy(), SetNet(32, 24, 12).init(1)
    history = train(net, data, TrainConfig(step=3e-3, batch=16, steps_per_epoch=20, epochs=6, values=20))
    assert history.loss[-1] < 0.5 * history.loss[0]
    held = toy(24, 9)
    h, g = zip(*((net.forward_h(x).mean(axis=0), net.forward_g(x).mean()) for x in held.inputs), strict=True)
    d = lambda i, j: ((h[i] - h[j]) ** 2).sum() + g[i] + g[j]
    same = [d(i, j) for i in range(24) for j in range(i) if held.variable[i] == held.variable[j]]
    other = [d(i, j) for i in range(24) for j in range(i) if held.variable[i] != held.variable[j]]
    assert np.mean([a < b for a in same for b in other]) > 0.95


def test_string_training_runs():
    data = Packed([str(i) for i in range(8)], [[f"{'AB'[i % 2]}{k:03d}" for k in range(6)] for i in range(8)], [i % 2 for i in range(8)])
    net = CharBiLstm(units=4, n_out=4, char_dim=4).init(1)
    h = train(net, data, TrainConfig(step=1e-2, batch=4, steps_per_epoch=5, epochs=6, values=4, augment=0.0))
    assert h.loss[-1] < h.loss[0]


def test_stop_rule():
    assert not should_stop([3, 2, 1], 2, 1e-3) and should_stop([3, 1, 1, 1], 2, 1e-3) and not should_stop([1, 1], 5, 0)


def test_samplers():
    d = np.array([[1.0, 2.0, 5.0, 9.0]])
    ok, rng = np.array([[True, True, True, False]]), np.random.default_rng(0)
    assert pick_negatives(d, ok, np.array([1.5]), "semihard", rng)[0] == 1
    assert pick_negatives(d, ok, np.array([7.0]), "semihard", rng)[0] == 2
    assert pick_negatives(d, ~ok & False, np.array([1.0]), "uniform", rng)[0] == -1
    near = [pick_negatives(d, ok, np.array([0.0]), "distance_weighted", rng)[0] for _ in range(300)]
    assert near.count(0) > near.count(2) and 3 not in near


def test_distributed_gradient(spark):
    from varlink.nets.train import gradient_step, train_distributed

    rng, net = np.random.default_rng(3), SetNet(4, 5, 3).init(1)
    rows = [tuple(rng.normal(size=8).tolist() for _ in range(3)) for _ in range(20)]
    df = spark.createDataFrame(rows, "anchor array<double>, positive array<double>, negative array<double>").repartition(3)
    loss, grad, n = gradient_step(net, df)
    sets = [[np.array(r[k]).reshape(-1, 4) for r in rows] for k in range(3)]
    want_loss, want = triplet_gradient(net, *sets)
    assert n == 20 and loss == pytest.approx(want_loss) and all(np.allclose(grad[k], want[k]) for k in want)
    assert len(train_distributed(net, df, TrainConfig(step=1e-2), 3).loss) == 3


def test_storage(spark, tmp_path):
    for net in (SetNet(3, 4, 2).init(5), CharBiLstm(units=3, n_out=2, char_dim=2).init(5)):
        save_model(spark, net, f"{tmp_path}/m", "m1")
        back, name = load_model(spark, f"{tmp_path}/m")
        assert name == "m1" and type(back) is type(net) and all((back.params[k] == v).all() for k, v in net.params.items())
