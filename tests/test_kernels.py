"""Kernels against the worked examples, brute force and invariants."""

import random
import warnings

import numpy as np
import pytest

from alignspark import workloads
from alignspark.functions.scoring import Scoring
from alignspark.operators import kernels as K
from alignspark.sources.tables import PRINTED, PRINTED_ROWS, PROFILE_ROWS

E, W, U = Scoring.experiment(), Scoring.worked_example(), Scoring.unit_edit()
PAIR_SCORES = [[14, 9, 13, 4, 8, 10], [8, 10, 6, 9, 8], [17, 22, 12, 21], [15, 16, 15], [13, 16], [12]]
EDITS = [[2, 10, 4, 11, 5, 8], [10, 5, 10, 4, 8], [8, 9, 9, 8], [8, 3, 7], [8, 10], [7]]


def words(rnd, n, top, letters="ACGT"):
    return ["".join(rnd.choice(letters) for _ in range(rnd.randint(0, top))) for _ in range(n)]


def test_worked_table():
    h = K.table(K.substitution("ATGCG", "TGCAT", W), -1)
    assert h.tolist() == [[0, -1, -2, -3, -4, -5], [-1, 1, 0, -1, 0, -1], [-2, 2, 2, 1, 0, 3], [-3, 1, 5, 4, 3, 2], [-4, 0, 4, 8, 7, 6], [-5, -1, 3, 7, 9, 8]]
    assert K.count_optimal("ATGCG", "TGCAT", W) == 2
    assert set(K.all_optimal("ATGCG", "TGCAT", W, 9)) == {("ATGCG_", "_TGCAT"), ("ATGC_G", "_TGCAT")}
    assert len(list(K.all_optimal("ATGCG", "TGCAT", W, 1))) == 1


def test_pair_fixtures():
    for table, s, sign in ((PAIR_SCORES, E, 1), (EDITS, U, -1)):
        for i, row in enumerate(table):
            for j, v in enumerate(row):
                assert K.scores([(PRINTED[i], PRINTED[i + 1 + j])], s)[0] == sign * v
    assert sum(map(sum, PAIR_SCORES)) == 258


def test_all_ways_to_a_score_agree():
    rnd = random.Random(1)
    for _ in range(80):
        a, b = words(rnd, 2, 25)
        for s in (E, W, U):
            v = K.scores([(a, b)], s)[0]
            for limit in (1 << 20, 0):
                moves, score = K.align_moves(a, b, s, limit=limit)
                x, y = K.spell(a, b, moves)
                m, o, g = K.pair_counts(x, y)
                assert (x.replace("_", ""), y.replace("_", "")) == (a, b) and score == v == m * s.match + o * s.mismatch + g * s.gap
            assert K.banded_score(a, b, s, 1)[0] == v == K.scores([(b, a)], s)[0]
        assert K.scores([(a, a)], E)[0] == 3 * len(a)
        for tie in ("dlu", "uld", "lud"):
            m, o, g = K.pair_counts(*K.spell(a, b, K.align_moves(a, b, E, tie)[0]))
            assert 3 * m - g == K.scores([(a, b)], E)[0]


def test_counts_without_a_traceback():
    rnd = random.Random(11)
    for s in (E, W, U, Scoring(2.5, -0.5, -1.25)):
        pairs = [tuple(words(rnd, 2, rnd.choice([3, 20, 40]), rnd.choice(["AC", "ACGT"]))) for _ in range(60)]
        for tie in ("dul", "dlu", "uld", "udl", "ldu", "lud"):
            want = [K.pair_counts(*K.spell(a, b, K.align_moves(a, b, s, tie)[0])) for a, b in pairs]
            assert K.path_counts(pairs, s, tie, 300).tolist() == [list(w) for w in want]


def test_scheme_checks():
    with pytest.raises(ValueError):
        Scoring(1, 1, -1).validate()
    with pytest.raises(ValueError):
        Scoring(1, 0, 1).validate()
    with warnings.catch_warnings(record=True) as seen:
        warnings.simplefilter("always")
        Scoring(3, -5, -1).validate()
    assert seen
    s = Scoring.matrix({("A", "G"): 1}, gap=-2, match=2, mismatch=-1)
    assert K.scores([("AC", "GC")], s)[0] == 3


def test_fixture_trees():
    d = K.distance_matrix(PRINTED, "edit", E)
    assert [j[:2] for j in K.neighbor_joining(d, "last").joins] == [(0, 1), (2, 4), (6, 8), (3, 9), (5, 7), (10, 11)]
    assert [j[:2] for j in K.agglomerative(d).joins] == [(0, 1), (3, 5), (7, 8), (6, 9), (2, 4), (10, 11)]
    a = np.array([[0, 5, 3, 6], [5, 0, 6, 9], [3, 6, 0, 5], [6, 9, 5, 0]], float)
    t = K.neighbor_joining(a, "last")
    assert t.joins[0] == (0, 1, 4, 1.0, 4.0, 0.0) and np.allclose(t.cophenetic(), a) and t.splits() == {frozenset({2, 3})}
    assert K.agglomerative(a).joins[0][:2] == (0, 2)
    u = np.full((4, 4), 8.0)
    u[0, 1] = u[1, 0] = 2
    u[2, 3] = u[3, 2] = 4
    np.fill_diagonal(u, 0)
    assert [j[5] for j in K.agglomerative(u).joins] == [1, 2, 4] and K.neighbor_joining(u).splits() == {frozenset({2, 3})}


def random_tree_matrix(rnd, n):
    t = K.random_tree(n, rnd.randint(0, 999))
    t.joins = [(a, b, k, rnd.randint(1, 9) / 2, rnd.randint(1, 9) / 2, h) for a, b, k, _, _, h in t.joins]
    return t, t.cophenetic()


def test_neighbor_joining_recovers_additive_matrices():
    rnd = random.Random(4)
    for _ in range(40):
        t, d = random_tree_matrix(rnd, rnd.randint(3, 12))
        for search in ("scan", "pruned"):
            for root in ("last", "midpoint"):
                made = K.neighbor_joining(d, root, search=search)
                assert np.allclose(made.cophenetic(), d) and made.splits() == t.splits()
        mid = K.neighbor_joining(d)
        assert sorted(mid.leaves()[mid.joins[-1][2]]) == list(range(len(d))) and len(mid.joins) == len(d) - 1
        back, names = K.parse_newick(mid.newick(digits=12))
        assert np.allclose(back.cophenetic(), d[np.ix_([int(x) for x in names], [int(x) for x in names])])


def test_linkages():
    rng = np.random.default_rng(5)
    for _ in range(30):
        n = int(rng.integers(2, 10))
        d = rng.random((n, n))
        d = np.triu(d, 1) + np.triu(d, 1).T
        for link in K.LINKAGES:
            scan, chain = K.agglomerative(d, link), K.agglomerative(d, link, "chain")
            assert [j[:3] for j in scan.joins] == [j[:3] for j in chain.joins]
            heights = [j[5] for j in scan.joins]
            assert heights == sorted(heights)
        # single linkage joins along a least spanning tree
        inside, total = {0}, 0.0
        while len(inside) < n:
            w, j = min((d[i, j], j) for i in inside for j in range(n) if j not in inside)
            inside.add(j)
            total += w
        assert np.isclose(sum(2 * j[5] for j in K.agglomerative(d, "single").joins), total)


def test_profile_and_ties():
    symbols, codes = K.coded(PROFILE_ROWS, "_")
    counts = sum(np.eye(len(symbols), dtype=int)[c] for c in codes)
    assert "".join(symbols[k] for k in K.consensus(counts, symbols, "first", 0, "", 0)) == "AGTGC"
    four = np.array([[1, 1, 1, 1, 0]])
    letters = ["A", "C", "G", "T", "_"]
    drawn = {letters[K.consensus(four, letters, "partner", seed, "f", 0, [4])[0]] for seed in range(60)}
    assert drawn == {"A", "C", "G", "T"}  # the partner's gap isn't among the tied
    assert letters[K.consensus(four, letters, "partner", 1, "f", 0, [2])[0]] == "G"
    assert K.consensus(four, letters, "partner", 1, "f", 0, [])[0] == K.consensus(four, letters, "partner", 1, "f", 0, None)[0]
    assert K.consensus(np.array([[1, 0, 0, 0, 3]]), letters, "first", 0, "", 0, gap_policy="exclude")[0] == 0


def check_rows(seqs, rows, s=E):
    assert [r.replace("_", "") for r in rows] == list(seqs)
    width = len(rows[0])
    assert all(len(r) == width for r in rows) and max(map(len, seqs)) <= width <= max(1, sum(map(len, seqs)))
    assert not any(all(r[k] == "_" for r in rows) for k in range(width))
    m, o, g = K.sum_of_pairs(rows, s)
    brute = [K.pair_counts(a, b) for i, a in enumerate(rows) for b in rows[i + 1 :]]
    assert (m, o, g) == tuple(map(sum, zip(*brute)))
    score, cost = s.match * m + s.mismatch * o + s.gap * g, (s.match - s.mismatch) * o + (s.match / 2 - s.gap) * g
    assert np.isclose(score, s.match * (len(rows) - 1) * sum(map(len, seqs)) / 2 - cost)
    assert score <= sum(K.scores([(a, b) for i, a in enumerate(seqs) for b in seqs[i + 1 :]], s))
    return score


@pytest.mark.parametrize("options", [{}, {"tie": "first"}, {"tie": "last"}, {"mode": "expected"}, {"gap_policy": "exclude"}, {"gap_symbol": "symbol"}, {"traceback": "lud"}])
def test_progressive_invariants(options):
    rnd = random.Random(6)
    for _ in range(15):
        seqs = [w or "A" for w in words(rnd, rnd.randint(2, 7), 14)]
        d = K.distance_matrix(seqs, "edit", E)
        for tree in (K.neighbor_joining(d), K.agglomerative(d), K.caterpillar(len(seqs)), K.random_tree(len(seqs), 3), K.star(d)):
            rows, _ = K.progressive(seqs, tree, K.Options(**options), "f")
            score = check_rows(seqs, rows)
            if len(seqs) == 2:
                assert options or score == K.scores([tuple(seqs)], E)[0]
            # a gap once placed stays: each inner node's rows, on their own, are what they were
            if len(seqs) > 2:
                sub = sorted(tree.leaves()[tree.joins[0][2]])
                small, _ = K.progressive([seqs[i] for i in sub], K.Tree(2, [(0, 1, 2, 0.0, 0.0, 0.0)]), K.Options(**{**options, "tie": "first"}), "f")
                cut = [k for k in range(len(rows[0])) if any(rows[i][k] != "_" for i in sub)]
                mine = ["".join(rows[i][k] for k in cut) for i in sub]
                assert [r.replace("_", "") for r in mine] == [seqs[i] for i in sub] and len(small[0]) == len(mine[0])


def test_printed_measures_and_edges():
    assert K.sum_of_pairs(PRINTED_ROWS, E) == (77, 79, 126)
    assert [r.replace("_", "") for r in PRINTED_ROWS] == PRINTED
    for seqs in (["A"], ["ACG", "ACG"], ["", "ACG"], ["", ""], ["", "", "AC"], ["AXN", "XN"], ["A", "ACGT" * 125]):
        d = K.distance_matrix(seqs, "mismatch_gap", E)
        rows, _ = K.progressive(seqs, K.agglomerative(d), K.Options(), "f")
        assert [r.replace("_", "") for r in rows] == seqs and len({len(r) for r in rows}) == 1


def test_exact_three_is_a_bound():
    rnd = random.Random(8)
    for _ in range(10):
        seqs = [w or "C" for w in words(rnd, 3, 7)]
        best = K.exact_three(*seqs, E)
        rows, _ = K.progressive(seqs, K.agglomerative(K.distance_matrix(seqs, "edit", E)), K.Options(), "f")
        assert check_rows(seqs, rows) <= best <= sum(K.scores([(a, b) for i, a in enumerate(seqs) for b in seqs[i + 1 :]], E))
    with pytest.raises(ValueError):
        K.exact_three("A" * 61, "A", "A", E)
    with pytest.raises(NotImplementedError):
        K.exact_many(["A"] * 4, E)


def test_added_sequence_keeps_old_gaps():
    rows = K.add_sequence(["AC_GT", "ACCGT"], "ACGGT", K.Options(), "f")
    assert [r.replace("_", "") for r in rows] == ["ACGT", "ACCGT", "ACGGT"] and len({len(r) for r in rows}) == 1


def test_grown_families_are_aligned_truly():
    for shape in workloads.SHAPES:
        seqs, rows = workloads.grow("ACGT" * 30, shape, "x")
        assert [r.replace("_", "") for r in rows] == seqs and len({len(r) for r in rows}) == 1
        assert workloads.true_tree(shape).splits() == {frozenset({3, 4}), frozenset({2, 3, 4})}


def test_distances():
    assert K.distance("ACGT", "ACGT", "mismatch_gap", E) == K.distance("ACGT", "ACGT", "kmer", E) == 0
    assert K.distance("", "", "mismatch_gap", E) == 0 and K.distance("AC", "A", "edit", E) == 1
    with pytest.raises(ValueError):
        K.distance("A", "A", "unknown", E)
    d = K.distance_matrix(PRINTED, "score_gap", E)
    assert d[2, 4] == 0 and np.allclose(d, d.T)


@pytest.mark.parametrize("scoring", [E, W, U, Scoring(match=1.5, mismatch=-0.25, gap=-0.75)])
def test_band_takes_the_path_of_the_whole_table(scoring):
    rnd = random.Random(11)
    for tie in ("dul", "lud", "udl"):
        for a, b in [*zip(words(rnd, 12, 60), words(rnd, 12, 60)), *((w, "".join(c for c in w if rnd.random() > 0.05)) for w in words(rnd, 12, 200)), ("ACGT" * 50, "A"), ("A", "ACGT" * 50)]:
            sub = K.substitution(a, b, scoring)
            if not sub.size:
                continue
            want = K.traceback(K.table(sub, scoring.gap), sub, scoring.gap, tie)
            for start in (1, 8):
                assert K.moves_in_band(lambda i, j0, j1: sub[i, j0:j1], len(a), len(b), scoring.gap, sub.max(), tie, sub.dtype.kind == "i", start) == want


def test_long_families_align_as_short_ones(monkeypatch):
    rnd = random.Random(12)
    root = "".join(rnd.choice("ACGT") for _ in range(150))
    seqs = ["".join(c for c in root if rnd.random() > 0.06) for _ in range(4)]
    for mode in ("consensus", "expected"):
        o = K.Options(mode=mode)
        d = K.distance_matrix(seqs, "mismatch_gap", E)
        want = K.progressive(seqs, K.neighbor_joining(d), o)
        with monkeypatch.context() as m:
            m.setattr(K, "CELLS", 100)
            assert (K.distance_matrix(seqs, "mismatch_gap", E) == d).all()
            assert K.progressive(seqs, K.neighbor_joining(d), o) == want


def test_chain_settles_ties_as_the_scan_does():
    rnd = np.random.default_rng(8)
    for n in (3, 5, 9):
        for _ in range(60):
            d = np.triu(rnd.integers(1, 6, (n, n)).astype(float), 1)
            d += d.T
            for linkage in K.LINKAGES:
                assert K.agglomerative(d, linkage, "chain").joins == K.agglomerative(d, linkage).joins


def test_large_tables_by_diagonals():
    import time

    rnd = random.Random(21)
    for k in range(150):
        scheme = (E, W, U, Scoring(2, -3, -1), Scoring(4, -1, -2))[k % 5]
        a, b = words(rnd, 2, rnd.choice([3, 30, 90]), rnd.choice(["AC", "ACGT", "AC_", "ACGT_"]))
        if k % 3 == 0:  # near copies, for narrow bands
            b = "".join(rnd.choice("ACGT") if rnd.random() < 0.05 else c for c in a if rnd.random() > 0.03)
        if not a or not b:
            continue
        symbols, (x, y) = K.coded([a, b])
        t = scheme.table(symbols)
        sub = t[x[:, None], y[None, :]]
        for tie in ("dul", "lud", "uld"):
            assert K.moves_by_diagonals(x, y, K._kinds(t), int(scheme.gap), tie, rnd.choice([2, 64])) == K.traceback(K.table(sub, scheme.gap), sub, scheme.gap, tie)
    assert K._kinds(Scoring.matrix({("A", "C"): 2}, -1).table(["A", "C", "G", "T"])) is None
    # a pair without likeness, which moves_in_band takes more than twice the time for
    a, b = ("".join(rnd.choice("ABFHM") for _ in range(9000)) for _ in range(2))
    symbols, (x, y) = K.coded([a, b])
    t, began = E.table(symbols), time.process_time()
    got = K.moves_of(x, y, t, -1)
    took, began = time.process_time() - began, time.process_time()
    rows = t[:, y]
    assert got == K.moves_in_band(lambda i, j0, j1: rows[x[i], j0:j1], len(x), len(y), -1, 3)
    assert took < (time.process_time() - began) / 2


def test_pairs_of_copies_are_taken_once(monkeypatch):
    seen = []
    of = K.distances
    monkeypatch.setattr(K, "distances", lambda pairs, *rest: seen.extend(pairs) or of(pairs, *rest))
    seqs = ["ACGT", "ACT", "ACGT", "ACT", "ACGT"]
    d = K.distance_matrix(seqs, "mismatch_gap", E)
    assert len(seen) == len(set(seen)) == 4
    assert d.tolist() == [[of([(a, b) if i < j else (b, a)], "mismatch_gap", E)[0] if i != j else 0 for j, b in enumerate(seqs)] for i, a in enumerate(seqs)]


def test_near_copies_take_the_path_of_the_whole_table(monkeypatch):
    rnd = random.Random(8)
    scoring, ends = Scoring.experiment(), []
    for _ in range(12):
        a = [rnd.choice("ACGT") for _ in range(rnd.randint(300, 500))]
        b = [c if rnd.random() > 0.04 else rnd.choice(["", "A", "GT", "_"]) for c in a]
        symbols, (x, y) = K.coded([a, "".join(b)], "_")
        t = scoring.table(symbols)
        sub = t[x[:, None], y[None, :]]
        moves = K.near_moves(x, y, t, scoring.gap)
        assert moves == K.traceback(K.table(sub, scoring.gap), sub, scoring.gap)
        ends.append(("".join(a), "".join(b).replace("_", "")))
    want = [K.path_counts([p], scoring)[0].tolist() for p in ends]
    monkeypatch.setattr(K, "_like", None)  # no whole tables
    monkeypatch.setattr(K, "table", None)
    assert K.path_counts(ends, scoring).tolist() == want
    seqs = [*ends[0], ends[0][0]]
    rows, _ = K.progressive(seqs, K.caterpillar(3), K.Options(scoring=scoring), "f")
    assert [r.replace("_", "") for r in rows] == seqs
