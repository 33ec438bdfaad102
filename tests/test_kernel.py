import itertools

import numpy as np
import pytest
from framedelta.model import EncoderSpec, ReuseConfig
from framedelta.operators import kernel, training
from framedelta.streaming.encoder import local_plan

SPEC = EncoderSpec.preset("tiny")


def video(n=21, seed=0, step=0.2):
    return np.cumsum(np.random.default_rng(seed).normal(size=(n, 6, 12)) * step, 0)


def plan(n=21):
    return local_plan(np.arange(n), ReuseConfig(), True)


def test_never_is_exact():
    raw = video()
    d = kernel.gated(raw, *plan(), SPEC, ReuseConfig(gate="never"), None)
    assert np.abs(d.emb - kernel.exact(raw, SPEC)).max() < 1e-12
    assert kernel.flops_gated(SPEC, d.reuse.sum(2), "never", False)[0] == kernel.flops_exact(SPEC)


@pytest.mark.parametrize("gate", ["mse", "budget", "learned", "always"])
def test_schedules_and_compactions_agree(gate):
    raw, m = video(), kernel.new_modules(SPEC)
    base = None
    for s, c, f in itertools.product(("layer", "frame"), ("batch", "frame", "none"), (True, False)):
        d = kernel.gated(raw, *plan(), SPEC, ReuseConfig(gate=gate, schedule=s, compaction=c, free_cache=f), m)
        base = base or d
        assert np.abs(d.emb - base.emb).max() < 1e-9 and (d.reuse == base.reuse).all()
    assert not base.reuse[:, :, 0].any() and not base.reuse[0].any()


def test_freed_caches_peak_lower():
    raw = video()
    deep = EncoderSpec.preset("deep")
    peak = {f: kernel.gated(raw, *plan(), deep, ReuseConfig(gate="mse", free_cache=f), None).count["peak"] for f in (True, False)}
    assert peak[True] * deep.layers <= peak[False]


def test_identical_frames_reuse_everything():
    raw = np.repeat(video(1), 21, 0)
    d = kernel.gated(raw, *plan(), SPEC, ReuseConfig(gate="mse", theta=1e-9, calibrator=False), None)
    assert np.abs(d.emb - kernel.exact(raw, SPEC)).max() < 1e-9
    assert d.reuse[1:20, :, 1:].all()


def test_budget_recomputes_exactly():
    raw = video(20)
    d = kernel.gated(raw, *local_plan(np.arange(20), ReuseConfig("sequential"), True), SPEC, ReuseConfig("sequential", gate="budget", budget=2, calibrator=False), None)
    assert ((~d.reuse[1:, :, 1:]).sum(2) == 2).all()


def test_reduction():
    raw = video(5)
    z, f = kernel.reduced(raw, SPEC, 0, 0)
    assert np.abs(z - kernel.exact(raw, SPEC)).max() < 1e-12 and f == kernel.flops_exact(SPEC)
    assert kernel.reduced(raw, SPEC, 1, 1)[1] < f
    assert np.isfinite(kernel.reduced(raw, SPEC, 3, 3)[0]).all()


def test_published_numbers():
    large = EncoderSpec.preset("large")
    per = kernel.flops_gated(large, np.full((1, large.layers), 0), "learned", True)[0] / kernel.flops_exact(large)
    assert per < 1.01
    n, d = 257, 1024
    assert abs(2 * 128 * (d + 3 * d) * n / (24 * n * d * d + 4 * n * n * d) - 0.04) < 0.002  # the calibrator is about 4 %
    offsets, _, _ = training.group_refs(3)
    assert [o + 1 for o in offsets] == [1, 5, 9, 13, 11, 12]


def test_gradients_by_differences():
    r = np.random.default_rng(0)
    g = np.cumsum(r.normal(size=(3, 6, 6, 12)) * 0.2, 1)
    _, refs, ft = training.group_refs(3)
    one = EncoderSpec.preset("tiny", layers=1)  # similarity and importance are constants to the tape, so one layer is exact
    exact = np.array([kernel.exact(x, one) for x in g])
    mods = kernel.new_modules(one)
    mods[0]["c2"] = r.normal(size=mods[0]["c2"].shape) * 0.05
    make = lambda: [{k: training.Var(v.copy()) for k, v in m.items()} for m in mods]
    noise = training.gumbel(1, 1, (1, 6, 3, 6))
    p = make()
    loss, _, _ = training.group_loss(g, refs, ft, one, p, exact, 1.0, noise, 0.9, 1.0)
    training.backward(loss)
    for key in mods[0]:
        for _ in range(3):
            i = tuple(r.integers(0, s) for s in mods[0][key].shape)
            got = []
            for e in (1e-5, -1e-5):
                q = make()
                q[0][key].v[i] += e
                got.append(float(training.group_loss(g, refs, ft, one, q, exact, 1.0, noise, 0.9, 1.0)[0].v))
            assert np.isclose((got[0] - got[1]) / 2e-5, 0 if p[0][key].g is None else p[0][key].g[i], atol=1e-6)


def test_soft_becomes_hard_and_equals_the_kernel():
    g = np.stack([video(6, s) for s in range(3)])
    _, refs, ft = training.group_refs(3)
    exact = np.array([kernel.exact(x, SPEC) for x in g])
    mods = kernel.new_modules(SPEC)
    p = [{k: training.Var(v) for k, v in m.items()} for m in mods]
    hard = training.group_loss(g, refs, ft, SPEC, p, exact, 1.0, None, 0.5, 1.0)
    cold = training.group_loss(g, refs, ft, SPEC, p, exact, 1e-6, np.zeros((2, 6, 3, 6)), 0.5, 1.0)
    assert np.isclose(hard[1], cold[1]) and np.isclose(hard[2], cold[2])
    past, future = (np.array(x) for x in zip(*refs, strict=True))
    d = [kernel.gated(x, past, future, ft, np.arange(6), SPEC, ReuseConfig(), mods) for x in g]
    assert np.isclose(hard[2], np.mean([x.reuse[1:, :, 1:].mean() for x in d]))
    assert np.isclose(hard[1], np.mean([kernel.cosine(x.emb, z)[1:].mean() for x, z in zip(d, exact, strict=True)]))


def test_training_lowers_the_loss():
    g = np.stack([video(6, s) for s in range(40)])
    _, log = training.fit_reuse(g, SPEC, r_target=0.6, steps=40, batch=40)
    assert np.mean([x[1] for x in log[-5:]]) < np.mean([x[1] for x in log[:5]])


def test_distributed_gradients(spark, small):
    """Gradients summed over tasks are those of all groups at once, for any number of tasks, and descent on them learns."""
    from framedelta.sources import frames as S

    f = S.activity(spark, small)
    spec = EncoderSpec.preset("tiny")
    one, log = training.fit_reuse_distributed(f, spec, steps=2, segments=1, partitions=1)
    many, again = training.fit_reuse_distributed(f, spec, steps=2, segments=1, partitions=5, at_once=7)
    for a, b in zip(one, many, strict=True):
        for k in a:
            assert np.allclose(a[k], b[k], atol=1e-8), k
    assert np.allclose(log, again)

    rows = training.whole_groups(f, spec, 1).orderBy("video_id", "e").collect()
    offsets, refs, ftype = training.group_refs(1)
    raw = np.array([[np.reshape(r["m"][o], (spec.n_tokens, spec.in_dim)) for o in offsets] for r in rows])
    modules = kernel.new_modules(spec, 5)
    cos, reuse, g_cos, g_reuse = training.gradients(raw, [(r.video_id, r.e) for r in rows], spec, modules, log[0][-1], 5, 1, 1)
    n = len(rows)
    assert np.isclose(log[0][2], cos / n) and np.isclose(log[0][3], reuse / n) and np.isclose(log[0][1], 1 - cos / n + max(0, 0.6 - reuse / n))
    # a step along the gradient lowers what it is the gradient of
    for g, at, sign in ((g_cos, 0, 1), (g_reuse, 1, 1)):
        moved, places = [], 0
        for m in modules:
            moved.append({})
            for k, v in m.items():
                moved[-1][k] = v - sign * 1e-3 * g[places : places + v.size].reshape(v.shape) / (np.linalg.norm(g) + 1e-12)
                places += v.size
        new = training.gradients(raw, [(r.video_id, r.e) for r in rows], spec, moved, log[0][-1], 5, 1, 1)
        assert new[at] > (cos, reuse)[at]


def test_distributed_training_of_a_share(spark, small):
    from framedelta.sources import frames as S

    f = S.activity(spark, small)
    _, log = training.fit_reuse_distributed(f, EncoderSpec.preset("tiny"), steps=4, segments=1, share=0.5, cos_target=0.9, partitions=2)
    assert len(log) == 4 and all(np.isfinite(x).all() for x in np.array(log))
    with pytest.raises(ValueError):
        training.fit_reuse_distributed(f.where("false"), EncoderSpec.preset("tiny"), steps=1)


@pytest.mark.parametrize("schedule", ["layer", "frame"])
def test_own_type_is_an_input(schedule):
    """Four more weights a hidden unit; with zeros there the decisions are those without, and a type can be barred from reuse."""
    raw, m = video(), kernel.new_modules(SPEC)
    wide = [{**x, "g1": np.vstack([x["g1"], np.zeros((4, x["g1"].shape[1]))])} for x in m]
    past, future, kind, wave = plan()
    run = lambda w: kernel.gated(raw, past, future, kind, wave, SPEC, ReuseConfig(schedule=schedule), w)
    a, b = run(m), run(wide)
    assert np.array_equal(a.reuse, b.reuse) and np.allclose(a.emb, b.emb)
    for x in wide:
        x["g1"][kernel.INPUTS + 3] = -1e3  # B1 frames: no hidden unit fires
        x["gb2"] = np.array([-0.5])
    c = run(wide)
    assert not c.reuse[kind == 3].any() and c.reuse[kind == 1].any()
    assert [x["g1"].shape[0] for x in kernel.new_modules(SPEC, own_type=True)] == [kernel.INPUTS + 4] * SPEC.layers
    g = np.stack([video(6, s) for s in range(12)])
    found, log = training.fit_reuse(g, SPEC, steps=5, batch=12, own_type=True)
    assert found[0]["g1"].shape[0] == 12 and np.isfinite(log[-1][1])
