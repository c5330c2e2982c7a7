"""The set form of the plane coder against a bit-by-bit loop, and coder round trips."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from gridpress.operators import planes as P
from gridpress.operators.entropy import CODERS, Model, ideal_bits


def loop(q: list[int], budget: float):
    """Visit planes and coefficients bit by bit; (runs by plane, stop plane, sent, sse)."""
    mask, sse, runs = set(), float(sum(x * x for x in q)), {}
    rest = list(q)
    if sse <= budget:
        return runs, 64, 0, sse
    for p in range(63, -1, -1):
        zero, runs[p], last = 0, [], 0
        for i, x in enumerate(q):
            b = x >> p & 1
            if i not in mask:
                last = b
                if b:
                    runs[p].append(zero)
                    zero = 0
                else:
                    zero += 1
            if b:
                sse -= float(rest[i]) ** 2 - float(rest[i] - (1 << p)) ** 2
                rest[i] -= 1 << p
            if b and i not in mask:
                mask.add(i)
            if sse <= budget * (1 + 1e-12):
                if not last and zero:
                    runs[p].append(zero)
                return runs, p, i + 1, sse
        if zero:
            runs[p].append(zero)
    return runs, 0, len(q), sse


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 2**20), min_size=1, max_size=40), st.floats(1e-6, 0.9))
def test_breakpoint_and_runs_equal_the_loop(q, share):
    v = np.array(q, np.uint64)
    budget = share * float((v.astype(float) ** 2).sum())
    runs, p, sent, _ = loop(q, budget)
    assert P.stop_by_budget(v, budget) == (p, sent)
    lead, neg = P.lead_array(v), np.zeros(len(q), bool)
    for plane in range(63, p, -1):
        assert P.split_plane(v, lead, neg, plane)[0].tolist() == runs[plane]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.floats(-1e6, 1e6, allow_nan=False), min_size=1, max_size=60), st.sampled_from(["range", "huffman"]))
def test_vector_round_trip(values, coder):
    from gridpress.operators.factors import decode_vector, encode_vector

    c = np.array(values)
    e = P.scale_exponent(float(np.abs(c).max()))
    got = decode_vector(encode_vector(c, 10, len(c), e, coder), len(c), 10, len(c), e, coder, midpoint=False)
    assert np.abs(got - c).max() <= 2.0 ** (e - 63 + 10) and (np.abs(got) <= np.abs(c)).all()


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 3000), max_size=3000), st.sampled_from(["range", "huffman"]))
def test_coders(runs, coder):
    r = np.array(runs, np.int64)
    m = Model.of(*np.unique(r, return_counts=True))
    assert CODERS[coder].decode(CODERS[coder].encode(r, m), m).tolist() == runs


def test_range_coder_is_close_to_the_ideal():
    r = np.random.default_rng(0).geometric(0.2, 200_000) - 1
    m = Model.of(*np.unique(r, return_counts=True))
    assert len(CODERS["range"].encode(r, m)) * 8 < 1.02 * ideal_bits(r)


@pytest.mark.parametrize("k", range(3, 53))
def test_exponent_just_under_a_power(k):
    assert P.scale_exponent(float(np.nextafter(2.0**k, 0))) == k - 1 and P.scale_exponent(2.0**k) == k


def test_worked_vector():
    q = np.array([18, 3, 0, 9, 1, 6, 2], np.uint64)
    assert P.lead_array(q).tolist() == [4, 1, -1, 3, 0, 2, 1]
    assert int((P.lead_array(q) > 1).sum()) == 3
    got = P.split_plane(q, P.lead_array(q), np.zeros(7, bool), 1)
    assert got[0].tolist() == [0, 2] and got[1].tolist() == [1, 0, 1]


def test_high_magnitudes_as_columns(spark):
    rows = [(0, 1.5 * 2.0**63), (1, 2.0**63), (2, float(np.nextafter(2.0**63, 0))), (3, 1.0), (4, 0.0)]
    got = P.quantise(spark.createDataFrame(rows, "idx long, v double"), exponent=63).orderBy("idx").collect()
    assert [r.q & (1 << 64) - 1 for r in got] == [3 << 62, 1 << 63, 2**63 - 1024, 1, 0]
    assert [r.lead for r in got] == [63, 63, 62, 0, -1]
    one = P.quantise(spark.createDataFrame([(0, -3.0), (1, 1.0)], "idx long, v double")).orderBy("idx").collect()
    assert one[0].lead == 63 and one[0].neg and one[1].lead == 62


def test_run_string_and_breakpoint(spark):
    df = spark.createDataFrame([(i, v) for i, v in enumerate([18, 3, 0, 9, 1, 6, 2])], "idx long, q long").withColumn("lead", P.lead_plane(P.F.col("q")))
    budget = 3.0
    p, sent = P.stop_by_budget(np.array([18, 3, 0, 9, 1, 6, 2], np.uint64), budget)
    got = P.breakpoint_sql(df, budget, range(6)).first()
    assert (got.plane, got.c_star + 1) == (p, sent)
    runs = {}
    for r in sorted(P.zero_runs(df, 0, 4).collect(), key=lambda r: (r.plane, r.seq)):
        runs.setdefault(r.plane, []).append(r.run)
    assert runs == {k: v for k, v in loop([18, 3, 0, 9, 1, 6, 2], 0.0)[0].items() if k < 5}
    fixed = P.negabinary_value(P.negabinary(P.F.lit(-7).cast("long")))
    assert spark.range(1).select(fixed.alias("v")).first().v == -7
