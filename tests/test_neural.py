import numpy as np
import pytest

from pairmatch.functions import neural as N, tape as T
from pairmatch.functions.templates import Template


def rows(n, seed):
    r = np.random.default_rng(seed)
    words, out = [f"w{i}" for i in range(200)], []
    for i in range(n):
        a = [words[j] for j in r.integers(0, 200, 8)]
        y = int(r.random() < 0.4)
        b = [x for x in a if r.random() < 0.7] if y else [words[j] for j in r.integers(0, 200, 6)]
        out.append({"pair_id": f"{seed}|{i}", "left_seq": "[COL] name [VAL] " + " ".join(a[:4]) + " [COL] x [VAL] " + " ".join(a[4:]), "right_seq": "[COL] title [VAL] " + " ".join(b), "y": y})
    return out


SMALL = N.NetConfig(dim=6, max_len=24)


@pytest.mark.parametrize("model", [N.ClozeMatcher(cfg=SMALL), N.HeadMatcher(SMALL), N.SiameseMatcher(SMALL), N.AttrRnnMatcher(SMALL), N.DomainAdaptMatcher(rows(8, 4), SMALL)])
def test_gradients_against_finite_differences(model):
    part = rows(4, 1)
    model.build()
    model.loss(part, None, 0).backward()
    for name, v in model.net.params.items():
        if v.grad is None:
            continue
        i = np.unravel_index(np.abs(v.grad).argmax(), v.grad.shape)
        at, h = v.v[i], 1e-5
        v.v[i] = at + h
        up = float(model.loss(part, None, 0).v)
        v.v[i] = at - h
        down = float(model.loss(part, None, 0).v)
        v.v[i] = at
        assert abs(v.grad[i] - (up - down) / (2 * h)) < 1e-4 * max(1e-2, abs(v.grad[i])), name


def test_learns_prunes_and_repeats():
    train, valid, test = rows(120, 1), rows(60, 2), rows(150, 3)
    m = N.ClozeMatcher(Template("t2", "soft")).fit(train, valid, 8, prune=(3, 0.2, 4))
    assert N.f1([r["y"] for r in test], m.predict(test) > 0.5) > 0.9
    assert [x["rows"] for x in m.log] == [120] * 3 + [96] * 3 + [77] * 2
    p = m.predict_passes(test, 3)
    assert np.allclose(p[::-1], m.predict_passes(test[::-1], 3))
    assert p.std(1).max() > 0


def test_two_adamw_steps_by_hand():
    v = T.Var(np.array([1.0]))
    opt = T.AdamW({"v": v}, lr=0.1, decay=0.0)
    for g in (2.0, 2.0):
        v.grad = np.array([g])
        opt.step()
    assert abs(v.v[0] - 0.8) < 1e-6


def test_augmentation_and_summary():
    r = {"pair_id": "1", "left_seq": "[COL] a [VAL] x y [COL] b [VAL] z", "right_seq": "q", "y": 1}
    assert N.augment(r, "swap", np.random.default_rng(0))["left_seq"] == "q"
    assert N.summarize("[COL] the rare", {"the": 0.1, "rare": 5.0}, 1) == "[COL] rare"
    assert N.knowledge("on 2024-01-02 for 3.50") == "on [DATE] 2024-01-02 for [PRICE] 3.50"
    with pytest.raises(RuntimeError):
        N.external("/nowhere")


def test_one_place_asks_as_all_places_did_and_texts_are_cut_once(monkeypatch):
    """The slot's vector and its gradients are those of attention made for every place; training cuts each text once."""
    net, rng = N.Net(SMALL).init(), np.random.default_rng(1)
    ids, at, keys = rng.integers(1, N.VOCAB, (5, 9)), np.array([0, 3, 8, 2, 5]), list("abcde")
    ids[1, 6:] = 0
    twin, found = rng.integers(0, 2, ids.shape), []
    for one in (lambda: T.pick(net.encode(ids, twin, keys, 3), (np.arange(5), at)), lambda: net.encode_at(ids, twin, at, keys, 3)):
        got = one()
        T.total(got * got).backward()
        found.append((got.v, {k: v.grad for k, v in net.params.items()}))
        for v in net.params.values():
            v.grad = None
    assert np.allclose(found[0][0], found[1][0], atol=1e-12)
    for k, g in found[0][1].items():
        assert np.allclose(g, found[1][1][k], atol=1e-10), k
    seen, cut = [], N.word_ids
    monkeypatch.setattr(N, "word_ids", lambda text, limit: seen.append(text) or cut(text, limit))
    for m in (N.ClozeMatcher(cfg=SMALL), N.HeadMatcher(SMALL), N.SiameseMatcher(SMALL)):
        seen.clear()
        m.fit(rows(20, 1), rows(10, 2), 4)
        assert len(seen) <= 4 * 30


def test_masks_come_from_numpys_own_seeding_and_seed_no_generator_a_key(monkeypatch):
    import hashlib

    keys, dim = [f"{i}|{i * 7}" for i in range(300)], 8
    want = []
    for k in keys:
        rng = np.random.default_rng(int.from_bytes(hashlib.md5(f"{k}|1003|1".encode()).digest()[:8], "little"))
        want.append((rng.random((5, dim)) >= 0.1) / 0.9)
    for s in (0, 1, 2**32 - 1, 2**32, 2**64 - 1):
        state = np.random.PCG64(s).state["state"]
        assert N._starts(np.array([s], np.uint64)) == [(state["state"], state["inc"])]

    def none(*args):
        raise AssertionError("a seed sequence a key")

    monkeypatch.setattr(np.random, "default_rng", none)
    assert np.array_equal(N.drop_mask(keys, (5, dim), 0.1, 1003, 1), np.stack(want))
    at = [i % 5 for i in range(300)]
    assert np.array_equal(N.drop_mask_at(keys, at, dim, 0.1, 1003, 1), np.stack([w[a] for w, a in zip(want, at)]))
