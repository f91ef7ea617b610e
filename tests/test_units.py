"""Small exact checks: paths, tensors, matching, subsumption, intrusion, entry points."""

import itertools
import os
import subprocess
import sys

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from momenttree.baselines import gibbs
from momenttree.evaluation import intrusion
from momenttree.evaluation.measures import revision_delta, variance
from momenttree.functions import paths
from momenttree.functions import tensor as X
from momenttree.operators import sampler
from momenttree.operators import tree as TT
from momenttree.plans import select
from momenttree.plans.build import choose_engine, condition_moments

HERE = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def test_paths():
    assert paths.level_of("o/1/2") == 2 and paths.parent_of("o/1/2") == "o/1" and paths.parent_of("o") is None
    assert paths.most_topics(10, 2) == 111 and paths.most_topics(1, 3) == 4
    tree = sampler.sample_tree((3, 2), 20, seed=1)
    assert (len(tree.nodes), len(tree.leaves()), tree.height()) == (10, 6, 2)


def test_permutations_place_the_named_modes():
    a = np.arange(27.0).reshape(3, 3, 3)
    for order in itertools.permutations((1, 2, 3)):
        out = X.permute(a, order)
        for i in itertools.product(range(3), repeat=3):
            assert out[i] == a[tuple(i[o - 1] for o in order)]


def test_third_moment_counts_distinct_triples():
    """Six tokens: every ordered triple of different positions, by brute force."""
    tokens = [0, 0, 1, 2, 2, 2]
    c = np.bincount(tokens, minlength=4).astype(float)
    want = np.zeros((4, 4, 4))
    for t in itertools.permutations(range(6), 3):
        want[tuple(tokens[i] for i in t)] += 1
    eye = np.eye(4)
    got = X.core_from(X.outer(c, c, c), X.outer(c, np.diag(c)), c, eye, np.zeros(4), 0.0, 1.0)
    assert np.allclose(got, want)


def test_multilinear_against_einsum():
    r = np.random.default_rng(0)
    t, a, b, v = r.normal(size=(4, 4, 4)), r.normal(size=(4, 2)), r.normal(size=(4, 3)), r.normal(size=4)
    assert np.allclose(X.multilinear(t, a, b, b), np.einsum("ijl,ia,jb,lc->abc", t, a, b, b))
    assert np.allclose(X.multilinear(t, np.eye(4), v, v), np.einsum("ijl,j,l->i", t, v, v))


def test_exact_moments_give_the_model_back():
    r = np.random.default_rng(2)
    alpha, phi = np.array([0.5, 0.3, 0.2]), r.dirichlet(np.full(30, 0.2), 3).T
    m1, e2, e3 = (X.population_moments(alpha, phi, k) for k in (1, 2, 3))
    m2, m3 = X.centred_moments(m1, e2, e3, 1.0)
    assert np.allclose(m3, sum(a * X.outer(p, p, p) for a, p in zip(alpha, phi.T, strict=True)))
    dense = X.whiten(*reversed(X.largest_eigs(m2, 3)))
    sigma, u = X.largest_eigs(e2, 3)
    lean = X.lean_whitener(u, sigma, m1, 1.0)
    for w in (dense, lean):
        assert np.allclose(w.w.T @ m2 @ w.w, np.eye(3), atol=1e-9)
        flat = X.recover(X.power_decompose(X.multilinear(m3, w.w, w.w, w.w), seed=1), w, 1.0)
        assert np.allclose(flat.alpha, alpha) and np.allclose(flat.phi, phi, atol=1e-8) and np.allclose(flat.share_sum, 1)
    assert np.allclose(X.u_terms(lean.w, m1, 1.0), X.u_terms(lean.w, m1, 1.0, e2))


def test_few_eigenpairs_of_a_large_matrix():
    r = np.random.default_rng(9)
    a = r.random((500, 60))
    m = a @ np.diag(r.normal(size=60)) @ a.T
    values, vectors = X.largest_eigs(m, 5)
    assert np.allclose(values, np.linalg.eigvalsh(m)[::-1][:5]) and np.allclose(m @ vectors, vectors * values, atol=1e-6)


def test_conditioning_exact_parent_gives_the_child():
    r = np.random.default_rng(3)
    alpha, phi = np.array([0.4, 0.6]), r.dirichlet(np.full(8, 0.5), 2).T
    m = [X.population_moments(alpha, phi, k) for k in (1, 2, 3)]
    for z in range(2):
        a, b, c = condition_moments(*m, alpha, phi, z)
        f = phi[:, z]
        assert np.allclose(a, f) and np.allclose(b, np.outer(f, f)) and np.allclose(c, X.outer(f, f, f))


def test_power_converges_quadratically_and_deflates():
    r = np.random.default_rng(4)
    q = np.linalg.qr(r.normal(size=(4, 4)))[0]
    t = sum(x * X.outer(v, v, v) for x, v in zip((4.0, 3.0, 2.0, 1.0), q.T, strict=True))
    found = X.power_decompose(t, seed=5, trace=True)
    assert np.allclose(found.values, (4, 3, 2, 1)) and found.residual < 1e-9
    assert len(X.power_decompose(t, seed=5, tol=1e-10, trace=True).trace[0]) < 30
    few = [X.power_decompose(t, starts=10, steps=10, seed=s).values for s in range(4)]
    assert np.ptp(few, axis=0).max() < 1e-6


@given(st.integers(1, 5), st.integers(0, 10**6))
@settings(max_examples=40, deadline=None)
def test_matching_against_all_permutations(n, seed):
    cost = np.random.default_rng(seed).random((n, n))
    got = X.best_matching(cost)
    assert np.isclose(sum(cost[i, c] for i, c in enumerate(got)), min(sum(cost[i, p[i]] for i in range(n)) for p in itertools.permutations(range(n))))


@given(st.lists(st.floats(-1, 1), min_size=1, max_size=8))
def test_simplex(values):
    p, clipped = X.to_simplex(np.array(values))
    assert np.isclose(p.sum(), 1) and (p >= 0).all() and clipped >= 0


def test_tree_algebra():
    tree = sampler.sample_tree((2, 2), 12, seed=1)
    assert np.allclose(tree.nodes["o/1"].phi, (tree.nodes["o/1/1"].phi + tree.nodes["o/1/2"].phi) / 2)
    cut = TT.collapse(tree, ["o/1"])
    assert sorted(cut.nodes) == ["o", "o/1", "o/2", "o/2/1", "o/2/2"] and cut.nodes["o/1"].status == "leaf"
    assert revision_delta(tree, cut, "o/1") == 0 and revision_delta(tree, cut, "o/2") == float("inf")
    assert variance([tree, tree, tree]) == 0
    turned = tree.copy()
    turned.nodes["o/1"], turned.nodes["o/2"] = tree.nodes["o/2"], tree.nodes["o/1"]
    assert TT.match_topics(tree, turned)["o/1"] == "o/2"


def test_selection():
    assert select.suggest_width(np.array([0.0130, 0.0081, 0.0047, 0.0013, 0.0006, 0.0005])) == 4
    assert select.suggest_width(np.array([1.0, 0.5, 0.04]), rule="threshold") == 2
    assert select.suggest_width(np.array([])) == 0
    assert choose_engine(1000, 1e12, 1e6) == "explicit"
    assert choose_engine(100_000, 1e8, 1e6) == "sparse" and choose_engine(10_000, 1e10, 1e6) == "implicit"


def test_intrusion():
    ranked = {f"o/{a}": [f"a{a}{i} b{a}{i}" for i in range(12)] for a in (1, 2)} | {f"o/{a}/{b}": [f"c{a}{b}{i}" for i in range(8)] for a in (1, 2) for b in (1, 2, 3)}
    for q in intrusion.phrase_intrusion(ranked, 50, seed=1):
        assert len(q["options"]) == 4 and q["options"][q["intruder"]] not in ranked[q["topic"]]
    assert intrusion.phrase_intrusion(ranked, 50, seed=1) == intrusion.phrase_intrusion(ranked, 50, seed=1)
    asked = intrusion.topic_intrusion(ranked, 40)
    assert len(asked) == 40
    npmi = {tuple(sorted(("c110", x))): 0.9 for x in ("c111", "c112")} | {("c111", "c112"): 0.9}
    assert intrusion.npmi_judge({"options": ["c110", "c111", "zz", "c112"], "intruder": 2}, npmi) == 2
    assert intrusion.npmi_judge({"options": ["x", "y"], "intruder": 0}, {}, 0.1) is None
    s = intrusion.score_intrusion([{"intruder": 0}, {"intruder": 1}], [[0, 0], [0, 0], [0, None]])
    assert (s["precision"], s["recall"]) == (0.5, 0.5)
    assert intrusion.score_intrusion([], [[]]) == {"precision": 0.0, "recall": 0.0, "f1": 0.0}


def test_entry_imports_without_the_training_data_operators(tmp_path):
    """A copy without that subpackage and the pipeline still lists all other queries; nothing else imports them."""
    import shutil

    for name in ("momenttree", "__spark_entry__.py"):
        source = os.path.join(HERE, name)
        (shutil.copytree if os.path.isdir(source) else shutil.copy)(source, tmp_path / name)
    shutil.rmtree(tmp_path / "momenttree" / "llm", ignore_errors=True)
    said = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; q = e.queries(); print(len(q), len(e.oracle_sql()), any(x.startswith('op1') for x in q))"], cwd=tmp_path, env=os.environ | {"PYTHONPATH": str(tmp_path)}, capture_output=True, text=True)
    n, m, has = said.stdout.split()
    assert int(n) > 90 and int(m) > 85 and has == "False", said.stderr


def test_guards():
    from momenttree.operators import moments

    with pytest.raises(moments.VocabularyTooLarge):
        moments.guard(1_001, 3, moments.DENSE_THIRD_WORDS)
    with pytest.raises(X.RankTooLow):
        X.whiten(np.eye(2), np.array([1.0, -0.1]))


def test_resampling_by_plain_numbers_draws_the_same(monkeypatch):
    """Labels, counts and totals are those of the array form, bit for bit; few topics take plain numbers."""
    random, made = np.random.default_rng(1), []
    docs = [random.integers(0, 9, n) for n in (1, 2, 50, 200)]
    labels = [random.integers(0, 3, len(d)) for d in docs]
    for few in (0, 16):
        monkeypatch.setattr(gibbs, "FEW_TOPICS", few)
        run, counts = gibbs.lda_resample(3, 0.1, 0.01), np.zeros((3, 9))
        for d, z in zip(docs, labels, strict=True):
            np.add.at(counts, (z, d), 1)
        totals = counts.sum(axis=1)
        drawn = [run(d, z.copy(), counts, totals, np.random.default_rng(k)) for k, (d, z) in enumerate(zip(docs, labels, strict=True))]
        made.append((run.__name__, np.concatenate(drawn), counts, totals))
    assert [m[0] for m in made] == ["run", "by_numbers"]
    assert all((a == b).all() for a, b in zip(made[0][1:], made[1][1:], strict=True))
    assert (made[0][1] != np.concatenate(labels)).any() and made[0][2].sum() == 253


def _three_chains(seeds=(4, 5, 6)):
    random = np.random.default_rng(2)
    docs = [random.integers(0, 9, n) for n in (3, 60, 1, 0, 17, 60)]
    sizes = np.array([len(d) for d in docs])
    block = gibbs.block_of(np.arange(6) + 10, sizes, np.concatenate(docs), 3, seeds)
    counts = np.zeros((3, len(seeds), 9))
    for c in range(len(seeds)):
        np.add.at(counts, (block.z[c].astype(int), c, block.words), 1)
    return docs, block, counts


def test_blocks_hold_every_word_in_its_place():
    docs, block, _ = _three_chains()
    for c in range(3):
        got = {d: words for d, words, z in block.documents(c) if len(words) == len(z)}
        assert got == {k + 10: d.tolist() for k, d in enumerate(docs)}
    assert (np.bincount(block.owners(), minlength=6) == block.sizes).all() and block.rows().sum() == 141


def test_a_block_of_one_document_draws_the_sequential_chain():
    random = np.random.default_rng(3)
    words, before = random.integers(0, 9, 300), random.integers(0, 50, (3, 9)).astype(float)
    block = gibbs.block_of(np.array([7]), np.array([300]), words, 3, (1,))
    z = block.z[0].astype(np.int64)
    np.add.at(before, (z, words), 1)
    counts, totals = before[:, None].copy(), before.sum(axis=1)[:, None]
    got = gibbs.side_by_side(block, counts, totals, 0.1, 0.01, block.random(1, 0).random(300)[None])
    own = before.copy()
    want = gibbs.lda_resample(3, 0.1, 0.01)(words, z.copy(), own, own.sum(axis=1), block.random(1, 0))
    assert (got[0] == want).all() and (want != z).any() and (counts[:, 0] == own).all() and (totals[:, 0] == own.sum(axis=1)).all()


def test_chains_of_a_block_do_not_touch_one_another():
    """Three chains at once draw what each draws alone; counts are those of the new labels."""
    draws = np.random.default_rng(5).random((3, 141))
    _, block, counts = _three_chains()
    totals = counts.sum(axis=2)
    together = gibbs.side_by_side(block, counts, totals, 0.1, 0.01, draws)
    for c, seed in enumerate((4, 5, 6)):
        _, alone, own = _three_chains((seed,))
        assert (gibbs.side_by_side(alone, own, own.sum(axis=2), 0.1, 0.01, draws[c : c + 1])[0] == together[c]).all() and (own[:, 0] == counts[:, c]).all()
    again = np.zeros_like(counts)
    for c in range(3):
        np.add.at(again, (together[c], c, block.words), 1)
    assert (again == counts).all() and (totals == counts.sum(axis=2)).all()
