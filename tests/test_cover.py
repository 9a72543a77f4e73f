"""Covers against recursive descent, and the tiling that proofs rely on."""

from hypothesis import given, settings
from hypothesis import strategies as st

from tsproof.functions import cover


def descend(lvl, idx, lo, hi, n, f):
    a, b = idx * f**lvl, min((idx + 1) * f**lvl, n) - 1
    if a > b or b < lo or a > hi:
        return []
    if lo <= a and b <= hi:
        return [(lvl, idx)]
    return [x for k in range(f) for x in descend(lvl - 1, idx * f + k, lo, hi, n, f)]


@settings(max_examples=300, deadline=None)
@given(st.integers(1, 300), st.sampled_from([2, 3, 4, 8, 16]), st.data())
def test_cover_is_recursive_descent(n, f, data):
    lo = data.draw(st.integers(0, n - 1))
    hi = data.draw(st.integers(lo, n - 1))
    assert sorted(cover.cover(lo, hi, n, f)) == sorted(descend(cover.depth_of(n, f), 0, lo, hi, n, f))


@settings(max_examples=300, deadline=None)
@given(st.integers(1, 300), st.sampled_from([2, 4]), st.data())
def test_proof_parts_tile_the_stream(n, f, data):
    lo = data.draw(st.integers(0, n))
    hi = data.draw(st.integers(lo - 1, n - 1))
    spans = sorted((i * f**lvl, min((i + 1) * f**lvl, n)) for part in cover.proof_parts(lo, hi, n, f).values() for lvl, i in part)
    assert [a for a, _ in spans] == [0, *[b for _, b in spans[:-1]]] and spans[-1][1] == n


def test_columns_agree_with_python(spark):
    rows = [(q, "s", lo, hi, n) for q, (lo, hi, n) in enumerate([(0, 0, 1), (3, 9, 10), (0, 9, 10), (5, 4, 10), (0, -1, 10), (10, 9, 10), (7, 200, 300), (1, 298, 300)])]
    for f in (2, 4):
        got = {}
        for r in cover.proof_keys(spark.createDataFrame(rows, "qid long, sid string, lo long, hi long, n long"), f).collect():
            got.setdefault(r["qid"], {}).setdefault(r["role"], set()).add((r["lvl"], r["idx"]))
        for q, _, lo, hi, n in rows:
            expected = {k: set(v) for k, v in cover.proof_parts(lo, hi, n, f).items() if v}
            assert got.get(q, {}) == expected
