"""Codes and decoders: the statements that are claimed of them, as properties."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from evenkeel.operators import codes, decode
from evenkeel.operators.decode import Decoder

CODES = [codes.block_code(6, 2), codes.block_code(12, 1), codes.block_code(12, 2), codes.ring_code(6, 2), codes.ring_code(7, 3), codes.ring_code(12, 1), codes.ring_code(12, 2), codes.ring_code(12, 3), codes.ring_code_closed(12, 1), codes.ring_code_closed(12, 2), codes.example3(), codes.full_copy_code(4), codes.identity_code(5)]
IDS = [f"{c.name}-{c.n}-{c.s}" for c in CODES]


@pytest.mark.parametrize("code", CODES, ids=IDS)
def test_any_answers_decode(code):
    ok, worst, failing, _ = decode.span_check(code)
    assert ok and failing is None and worst < 1e-7
    d = Decoder(code)
    for alive in codes.patterns(code.n, code.s, 300):
        a = d.row(alive)
        assert decode.residual(code, a) < 1e-7 and set(np.flatnonzero(a)) <= set(alive)


@pytest.mark.parametrize("code", [c for c in CODES if c.n > c.s + 1], ids=[i for c, i in zip(CODES, IDS, strict=True) if c.n > c.s + 1])
def test_one_more_late_worker_is_too_many(code):
    assert not decode.span_check(code, code.s + 1)[0]


@pytest.mark.parametrize("code", CODES, ids=IDS)
def test_density_meets_the_bound(code):
    assert (np.count_nonzero(code.matrix, axis=0) >= code.s + 1).all()
    if code.name != "example3":
        assert (code.density() == codes.density_bound(code.n, code.k, code.s)).all()


def test_block_layout():
    b = codes.block_code(6, 2)
    assert [b.support(w).tolist() for w in range(6)] == [[0, 1, 2], [3, 4, 5]] * 3
    with pytest.raises(ValueError):
        codes.block_code(7, 2)


@given(st.integers(2, 9), st.data())
@settings(max_examples=40, deadline=None)
def test_ring_code_of_any_size(n, data):
    s = data.draw(st.integers(0, n - 1))
    code = codes.ring_code(n, s, seed=data.draw(st.integers(0, 99)))
    alive = data.draw(st.permutations(range(n)))[: n - s]
    a = Decoder(code).row(alive)
    assert a is not None and np.abs(a @ code.matrix - 1).max() < 1e-6
    assert [set(code.support(w)) <= set(codes.ring_support(n, s)[w]) for w in range(n)] == [True] * n


def test_edges_of_s():
    assert (codes.ring_code(5, 0).matrix == np.eye(5)).all()
    assert (codes.ring_code(5, 4).matrix == 1).all()
    assert (codes.block_code(5, 4).matrix == 1).all()


def test_ring_rows_are_in_the_null_space():
    h = codes.zero_sum_matrix(9, 3, np.random.default_rng(4))
    code = codes._from_null_space(h, 9, 3, "ring")
    assert np.abs(h @ code.matrix.T).max() < 1e-9 and np.abs(h.sum(axis=1)).max() < 1e-12
    assert codes.mds_check(h, 3)[0]
    assert all(np.linalg.matrix_rank(code.matrix[list(p)]) == 6 for p in codes.patterns(9, 3, 30))


def test_integer_matrix_fails_where_it_must():
    assert not codes.mds_check(codes.integer_null_matrix(5, 2), 2)[0]
    with pytest.raises(ValueError):
        codes.ring_code_closed(8, 2)


def test_best_draw_grows_less():
    assert codes.growth(codes.ring_code(12, 2, 3)) <= codes.growth(codes.ring_code(12, 2, 3, select="first"))


def test_chain_row():
    h = codes.integer_null_matrix(12, 1)
    code = codes.ring_code_closed(12, 1)
    for late in range(12):
        a = decode.chain_row_s1(h[0], late)
        assert a[late] == 0 and decode.residual(code, a) < 1e-9


def test_decoder_keeps_rows():
    d = Decoder(codes.ring_code(6, 2))
    for _ in range(5):
        d.row([0, 2, 3, 5])
    assert d.solved == 1 and d.hits == 4


def test_policies_agree_on_the_sum():
    code, g = codes.block_code(6, 2), np.arange(12.0).reshape(6, 2)
    for policy in ("pick_first", "min_norm"):
        a = decode.decode_row(code, [1, 2, 4, 5], policy)
        assert np.allclose(a @ code.matrix @ g, g.sum(axis=0))


def test_unrank_is_lexicographic():
    from itertools import combinations

    assert [tuple(decode.unrank(i, 7, 4)) for i in range(35)] == list(combinations(range(7), 4))


def test_decode_table(spark):
    code = codes.ring_code(6, 2)
    rows = decode.decode_table(spark, code).collect()
    for p in range(15):
        a = np.zeros(6)
        for r in rows:
            if r.pattern == p:
                a[r.worker] = r.coef
        assert decode.residual(code, a) < 1e-7
    with pytest.raises(ValueError):
        decode.decode_table(spark, codes.Code(np.eye(100), 6, "big"))


def test_approximate_row():
    a, error = decode.approx_row(codes.ring_code(12, 2), range(8))
    assert error > 0.1 and set(np.flatnonzero(a)) <= set(range(8))


def test_two_stage_shares():
    t = codes.two_stage(3, 1, 2.0, "ring")
    assert t.load == pytest.approx(4 / 9) and t.plain_share + t.coded_share == pytest.approx(1)
    for alpha in (1.2, 1.5, 2, 3):
        for s in (1, 2):
            t = codes.two_stage(12, s, alpha)
            plain, coded = t.plain_share / 12, t.coded_share * (s + 1) / 12
            assert alpha * plain == pytest.approx(plain + coded)  # a slowed worker ends its plain part in time
            assert t.load == pytest.approx(plain + coded)
    assert codes.two_stage(12, 1, 1.2).coded_share == pytest.approx(1 / 11)
    with pytest.raises(ValueError):
        codes.two_stage(12, 1, 1.0)
