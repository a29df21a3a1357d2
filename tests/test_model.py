import numpy as np
import pyarrow as pa
import pytest

from lexbridge.operators import model as M
from lexbridge.operators.encoder import VisibleEncoder, bag, bags
from lexbridge.operators.inject import visible_mask

CFG = M.TrainConfig(dims=12, hidden=3)


def setup(hier=False):
    rng = np.random.default_rng(1)
    net = M.new_net(CFG, 4, hier)
    net.p["A"] = rng.standard_normal(net.p["A"].shape)
    if hier:
        net.p["S"] = rng.standard_normal(net.p["S"].shape)
    x = np.abs(rng.standard_normal((6, 12))) * (rng.random((6, 12)) < 0.7)
    k = rng.random((6, 4))
    return net, x, k, M.Batch(x, np.array([1, -1, 1, -1, -1, 1.0]), x, x[::-1] + 0.1, m_lab=x * 0.5)


def numeric(net, name, f, eps=1e-6):
    v, out = net.p[name], np.zeros_like(net.p[name])
    for i in np.ndindex(v.shape):
        old = v[i]
        v[i] = old + eps
        hi = f()
        v[i] = old - eps
        lo = f()
        v[i] = old
        out[i] = (hi - lo) / (2 * eps)
    return out


@pytest.mark.parametrize("hier", [False, True])
def test_label_gradient(hier):
    net, _, _, b = setup(hier)
    _, g = M.label_loss(net, b, True)
    for name in g:
        assert np.allclose(g[name], numeric(net, name, lambda: M.label_loss(net, b, True)[0]), atol=1e-6), name


def test_pivot_and_sign_gradients():
    net, x, k, _ = setup()
    _, g = M.pivot_loss(net, x, k)
    for name in g:
        assert np.allclose(g[name], numeric(net, name, lambda: M.pivot_loss(net, x, k)[0]), atol=1e-6), name
    net, x, k, _ = setup(True)
    s = (k[:, :2] > 0.5).astype(float)
    _, g = M.sign_loss(net, x, s)
    for name in g:
        assert np.allclose(g[name], numeric(net, name, lambda: M.sign_loss(net, x, s)[0]), atol=1e-6), name


def test_domain_gradient_is_reversed_for_the_projection_only():
    net, _, _, b = setup()
    _, g = M.domain_loss(net, b.xs, b.xt, 0.5)
    f = lambda: M.domain_loss(net, b.xs, b.xt, 0.5)[0]
    assert np.allclose(g["E"], -0.5 * numeric(net, "E", f), atol=1e-6)
    assert np.allclose(g["D"], numeric(net, "D", f), atol=1e-6)


def test_fit_lowers_the_loss_and_separates():
    rng = np.random.default_rng(0)
    y = np.where(rng.random(60) < 0.3, 1.0, -1.0)
    x = rng.random((60, 12)) * 0.1
    x[y > 0, 0] = 1
    net = M.fit(M.new_net(CFG, 1), M.Batch(x, y, x, x), CFG)
    assert net.history[-1] < net.history[0] and ((net.p_pos(x) > 0.5) == (y > 0)).mean() > 0.95


def test_warm_up_and_one_class():
    assert M.warm(0, 100, 0.1) == pytest.approx(0.1) and M.warm(50, 100, 0.1) == 1
    x = np.ones((3, 12))
    assert np.isfinite(M.fit(M.new_net(CFG, 1), M.Batch(x, np.ones(3), x, x), CFG).history[-1])


def test_attention_sees_only_what_the_tree_allows():
    branch, trunk = np.array([0, 1, 1, 0]), np.array([0, 0, 0, 1])
    mask = visible_mask(branch, trunk)
    assert (mask == mask.T).all() and mask.diagonal().all() and not mask[1, 3] and mask[0, 1] and mask[0, 3]
    rng = np.random.default_rng(0)
    _, att = VisibleEncoder(rng.standard_normal((50, 16))).run(["a", "b", "c", "d"], np.arange(4), branch, trunk)
    assert np.allclose(att.sum(axis=2), 1) and (att[:, ~mask] == 0).all()


def test_bag_without_branches_is_the_plain_bag():
    trunk = [{"tok": "a", "pos": 0, "branch": 0, "trunk": 0}]
    with_branch = trunk + [{"tok": "zz", "pos": 1, "branch": 1, "trunk": 0}]
    assert [list(v) for v in bag(with_branch, 64, 0.0)] == [list(v) for v in bag(trunk, 64, 0.0)]
    assert len(bag(with_branch, 64, 0.5)[0]) == 2 and len(bag([], 64, 0.5)[0]) == 0


def test_bags_of_many_texts_equal_those_of_each():
    rng = np.random.default_rng(3)
    tok = lambda n: [{"tok": f"w{rng.integers(30)}", "pos": int(k + b), "branch": int(b and k * 64 + b), "trunk": k} for k in range(n) for b in (0, 1, 2)[: 1 + 2 * int(rng.integers(2))]]
    texts, sets, of = [tok(n) for n in (40, 0, 7, 1, 300)], [frozenset({"w1", "w2"}), frozenset()], np.array([0, 1, 0, 1, 0])
    kind = pa.list_(pa.struct([("tok", pa.string()), ("pos", pa.int32()), ("branch", pa.int32()), ("trunk", pa.int32())]))
    got = list(bags(pa.array([*texts, None], kind)[:5], 64, 0.5, sets, of))
    for t, s, (ix, v, mix, mv, piv) in zip(texts, of, got, strict=True):
        assert [x.tolist() for x in (*bag(t, 64, 0.5), *bag(t, 64, 0.5, sets[s]))] == [x.tolist() for x in (ix, v, mix, mv)]
        assert piv == sorted({x["tok"] for x in t if x["branch"] == 0 and x["tok"] in sets[s]})
    assert [x[0].tolist() for x in bags(pa.array(texts, kind), 64, 0.5)] == [bag(t, 64, 0.5)[0].tolist() for t in texts]
