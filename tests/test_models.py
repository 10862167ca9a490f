"""Hand-worked examples, gradient checks and invariants of the models and measures."""

import numpy as np
import pytest

from tracegroup.operators import bpe, nn
from tracegroup.operators.baselines import frame_edit_distance
from tracegroup.operators.encoder import CrossEncoder, EncoderConfig, TraceEncoder, shared_marks, unit
from tracegroup.operators.losses import bce_pair, info_nce
from tracegroup.operators.neural_baselines import PairHead, pairwise_step
from tracegroup.operators.train import TrainConfig, contrastive_step, triplet_step

TINY = EncoderConfig(vocab=12, token=3, frame=2, trace=2, seed=4)
RNG = np.random.default_rng(0)


def trace(*frames):
    return [np.array(f, np.int32).tobytes() for f in frames]


TRACES = [trace([2, 3], [4]), trace([4], [5, 6, 7], [2, 3]), trace([8]), trace([9, 2], [9, 2], [3])]
OTHERS = [trace([4], [2, 3], [3]), trace([5, 6, 7]), trace([8], [10]), trace([11], [9, 2])]


def numeric(f, params, grads, keys):
    for k in keys:
        flat, g = params[k].ravel(), np.asarray(grads[k]).ravel()
        for i in RNG.choice(len(flat), min(6, len(flat)), replace=False):
            old = flat[i]
            flat[i] = old + 1e-6
            up = f()
            flat[i] = old - 1e-6
            down = f()
            flat[i] = old
            assert abs((up - down) / 2e-6 - g[i]) < 1e-5 + 1e-4 * abs(g[i]), (k, i)


@pytest.mark.parametrize("pool", nn.POOLS)
@pytest.mark.parametrize("frames", ["bilstm", "mean"])
@pytest.mark.parametrize("denominator", ["negatives", "all"])
def test_contrastive_gradients(pool, frames, denominator):
    model = TraceEncoder(EncoderConfig(vocab=12, token=3, frame=2, trace=2, pool=pool, frame_encoder=frames, seed=4))
    config = TrainConfig(denominator=denominator, tau=0.5)
    step = lambda: contrastive_step(model, TRACES, OTHERS, [1, 2, 3, 4], config)
    _, grads = step()
    numeric(lambda: step()[0], model.params, grads, list(model.params))


@pytest.mark.parametrize("marker", [True, False])
def test_triplet_gradients(marker):
    model = CrossEncoder(TINY, use_marker=marker)
    step = lambda: triplet_step(model, TRACES, OTHERS, OTHERS[::-1])
    _, grads = step()
    numeric(lambda: step()[0], model.params, grads, list(model.params))


def test_marker_and_order():
    model = CrossEncoder(EncoderConfig(vocab=12, token=6, frame=5, trace=8, seed=4))
    pair = [(TRACES[0], OTHERS[0])]
    apart = [(TRACES[2], OTHERS[1])]
    with_marker, alone = model.forward(pair)[0], model.forward(apart)[0]
    model.params["r.marker"] *= 0
    assert not np.allclose(with_marker, model.forward(pair)[0]) and np.allclose(alone, model.forward(apart)[0])
    assert not np.allclose(model.forward(pair)[0], model.forward([pair[0][::-1]])[0])
    q, c = shared_marks([b"a", b"b", b"c", b"b"], [b"x", b"b"])
    assert q.tolist() == [False, True, False, True] and c.tolist() == [False, True]


def test_pairwise_gradients():
    model = TraceEncoder(TINY)
    head = PairHead(model.params, model.width)
    step = lambda: pairwise_step(model, head, TRACES, OTHERS, OTHERS[::-1])
    _, grads = step()
    numeric(lambda: step()[0], model.params, grads, list(model.params))
    u, v = RNG.normal(size=(3, model.width)), RNG.normal(size=(2, model.width))
    want = [[head.forward(a[None], b[None])[0][0] for b in v] for a in u]
    assert np.allclose(head.all_pairs()(u, v), want)


def test_padding_does_not_count():
    model = TraceEncoder(TINY)
    one = np.concatenate([model.forward([t])[0] for t in TRACES + [[]]])
    assert np.allclose(one, model.forward(TRACES + [[]])[0])


def test_losses_by_hand():
    s = np.array([[0.5, 0.2], [0.1, 0.4]])
    assert np.isclose(info_nce(s, 1.0)[0], ((-0.5 + 0.2) + (-0.4 + 0.1)) / 2)
    assert np.isclose(info_nce(s, 1.0, "all")[0], (np.log(1 + np.exp(-0.3)) * 2) / 2)
    assert np.isclose(bce_pair(np.zeros(1), np.zeros(1))[0], 2 * np.log(2))
    assert bce_pair(np.array([-800.0]), np.array([800.0]))[0] == 1600
    same = np.ones((2, 2), bool)
    assert info_nce(s, 1.0, "negatives", same)[0] == 0


def test_pools_by_hand():
    out = np.array([[[1.0, 4], [3, 2], [9, 9]]])
    last = np.array([[7.0, 8]])
    n = np.array([2])
    assert nn.pooled(out, last, n, "avg")[0].tolist() == [[2, 3]]
    assert nn.pooled(out, last, n, "max")[0].tolist() == [[3, 4]]
    assert nn.pooled(out, last, n, "all")[0].tolist() == [[2, 3, 3, 4, 7, 8]]


def plain_bpe(words, merges):
    now = {tuple([*w, bpe.END]): n for w, n in words.items()}
    done = []
    for _ in range(merges):
        count = {}
        for w, n in now.items():
            for p in zip(w, w[1:]):
                count[p] = count.get(p, 0) + n
        if not count:
            break
        best = min(count, key=lambda p: (-count[p], p))
        if count[best] < 2:
            break
        done.append(best)
        nxt = {}
        for w, n in now.items():
            out, i = [], 0
            while i < len(w):
                if w[i : i + 2] == best:
                    out.append(w[i] + w[i + 1])
                    i += 2
                else:
                    out.append(w[i])
                    i += 1
            nxt[tuple(out)] = n
        now = nxt
    return done


def test_bpe(spark):
    words = {"low": 5, "lower": 2, "newest": 6, "widest": 3, "aaaa": 2}
    model = bpe.learn(words)
    assert model.merges == plain_bpe(words, 1000)
    for w in [*words, "lowest", "x", ""]:
        assert "".join(model.symbols(w)) == w + bpe.END
    assert bpe.UNKNOWN not in model.encode("slow")  # an unseen word of seen signs has no unknown token
    counts = spark.createDataFrame(list(words.items()), "piece string, n long")
    assert bpe.rounds(counts, per_round=1).merges[:6] == model.merges[:6]
    small = bpe.learn(words, vocab_size=16)
    assert len(small.vocab) + 2 <= 16


def test_frame_edit_distance():
    assert frame_edit_distance(list("kitten"), list("sitting")) == 3
    assert frame_edit_distance([], ["a"]) == 1 and frame_edit_distance([], []) == 0
    assert frame_edit_distance(list("abcd"), list("dabc")) == 2


def test_unit_rows():
    assert np.allclose(np.linalg.norm(unit(np.array([[3.0, 4], [0, 0]])), axis=1), [1, 0])


def test_whole_traces_and_frames():
    """Registered configurations read past the 64th frame and the 24th token, and marks count there; memory is cut by length only."""
    from tracegroup.operators import encoder, neural_baselines
    from tracegroup.plans import two_stage

    assert two_stage.SMALL.vocab == 10_000
    one = lambda k: np.full(1, k, np.int32).tobytes()
    for config in (two_stage.SMALL, neural_baselines.SMALL):
        model = TraceEncoder(config)
        a = [one(i % 50 + 2) for i in range(400)]
        u = model.forward([a, a[:399] + [one(60)], a[:3]])[0]
        assert np.abs(u[0] - u[1]).max() > 0
        long = np.arange(2, 90, dtype=np.int32)
        v = model.forward([[long.tobytes()], [np.append(long, 99).astype(np.int32).tobytes()]])[0]
        assert np.abs(v[0] - v[1]).max() > 0
        assert np.allclose(model.forward([a, a[:3]], keep=False)[0], u[[0, 2]])
    cross = CrossEncoder(two_stage.SMALL)
    marked = cross.encoder.forward([a, a], [np.arange(400) == 399, np.zeros(400, bool)], cross.params["r.marker"])[0]
    assert np.abs(marked[0] - marked[1]).max() > 0
    groups = encoder.by_length([range(n) for n in (5, 0, 3, 40, 2)], 10)
    assert sorted(i for g in groups for i in g) == [0, 1, 2, 3, 4] and groups[-1].tolist() == [3]


def test_every_name_has_a_vector_of_its_own(spark):
    """Names outside the trained table, and names that training has not seen, differ from one another."""
    from pyspark.sql import functions as F

    from tracegroup.operators import neural_baselines as nb
    from tracegroup.operators.train import as_bytes

    rows = [(f"f{i}", [f"name{i}"], "train" if i < 20 else "test") for i in range(40)]
    reports = spark.createDataFrame(rows, "fp string, frames array<string>, part string").withColumn("arrival_seq", F.lit(1))
    toks, ids = nb.names_as_tokens(reports, lambda f: f, 7)
    traces = {r["fp"]: as_bytes(r["toks"]) for r in toks.collect()}
    model = TraceEncoder(nb.SMALL)
    out, cache = model.forward([traces[f"f{i}"] for i in range(40)])
    assert len(ids) == 5 and len({v.tobytes() for v in out.round(9)}) == 40
    assert np.array_equal(out, TraceEncoder(nb.SMALL).forward([traces[f"f{i}"] for i in range(40)])[0])
    grads = {}
    model.backward(np.ones_like(out), cache, grads)
    assert set(np.flatnonzero(np.abs(grads["e.tokens"]).sum(1))) == set(ids.values())
