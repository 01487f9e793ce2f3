from collections import Counter

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from lexfold.operators.kernel import Options, Shard, fold_units, token_cost, unfold_units

U = lambda **k: Options(cost="unit", **k)
MIXED = "a b c d a b c d a b e a b g a b h a b i"
CASES = [
    ("a a a a a a a a", 2, "<M1> <M1> <M1> <M1>", ["a a"]),
    ("a a a a a a a a", 4, "<M1> <M1>", ["a a a a"]),
    ("a a a a a a a a", 3, "<M1> <M1> <M1> <M1>", ["a a"]),
    ("x y z x y z x y z q", 3, "<M1> <M1> <M1> q", ["x y z"]),
    ("a b c a b d a b e", 2, "a b c a b d a b e", []),
    ("p q r p q r p q r p q r", 2, "<M1> r <M1> r <M1> r <M1> r", ["p q"]),
    ("p q r p q r p q r p q r", 3, "<M1> <M1> <M1> <M1>", ["p q r"]),
    ("<M1> k l m n k l m n", 4, "<M1> <M2> <M2>", ["k l m n"]),
    ("", 5, "", []),
    ("one", 5, "one", []),
    ("a b c d e", 5, "a b c d e", []),
]


@pytest.mark.parametrize(("text", "l_max", "folded", "legend"), CASES)
def test_goldens(text, l_max, folded, legend):
    got = fold_units(text.split(), U(l_max=l_max))
    assert " ".join(got.folded) == folded
    assert [" ".join(e.units) for e in got.legend] == legend


def test_ratios():
    got = fold_units("x y z x y z x y z q".split(), U(l_max=3))
    assert (round(got.cr, 9), round(got.cr_input, 9)) == (0.6, 0.2)
    short, long = fold_units(MIXED.split(), U(l_max=2)), fold_units(MIXED.split(), U(l_max=4))
    assert (round(short.cr, 2), round(short.cr_input, 2)) == (0.30, 0.15)
    assert (round(long.cr, 2), round(long.cr_input, 2)) == (0.50, 0.10)
    assert not fold_units("x y z x y z x y z q".split(), Options(cost="pieces", l_max=3)).legend


def slow(units, l_max, f_min=2, l_min=2, cost="unit"):
    """Rewrites the sequence after each length, on lists."""
    seq, number, legend = [(u, False) for u in units], 1, {}
    literal = {u for u in units if u.startswith("<M")}
    for length in range(l_max, l_min - 1, -1):
        where = {}
        for i in range(len(seq) - length + 1):
            if not any(m for _, m in seq[i : i + length]):
                where.setdefault(tuple(u for u, _ in seq[i : i + length]), []).append(i)
        used, put = set(), {}
        for gram in sorted((g for g in where if len(where[g]) >= f_min), key=lambda g: (-len(where[g]), where[g][0])):
            spots, last = [], -length
            for p in where[gram]:
                if used.isdisjoint(range(p, p + length)) and p >= last + length:
                    spots.append(p)
                    last = p
            while f"<M{number}>" in literal:
                number += 1
            s, m, f = sum(token_cost(u, cost) for u in gram), token_cost(f"<M{number}>", cost), len(spots)
            if f >= f_min and (1 + f) * m + s < f * s:
                legend[f"<M{number}>"] = list(gram)
                for p in spots:
                    used |= set(range(p, p + length))
                    put[p] = f"<M{number}>"
                number += 1
        new, i = [], 0
        while i < len(seq):
            if i in put:
                new.append((put[i], True))
                i += length
            else:
                new.append(seq[i])
                i += 1
        seq = new
    return [u for u, _ in seq], legend


texts = st.lists(st.sampled_from(["a", "b", "cc", "7x9", "<M2>"]), max_size=60)


@settings(max_examples=150, deadline=None)
@given(texts, st.integers(2, 6), st.sampled_from(["unit", "pieces"]))
def test_equals_slow_rewriting(units, l_max, cost):
    got = fold_units(units, Options(l_max=l_max, cost=cost, guard=False))
    folded, legend = slow(units, l_max, cost=cost)
    assert got.folded == folded
    assert {e.marker: e.units for e in got.legend} == legend


@settings(max_examples=150, deadline=None)
@given(texts, st.integers(1, 6), st.sampled_from(["frequency", "savings"]), st.booleans(), st.sampled_from(["asc", "desc"]), st.sampled_from(["actual", "fixed"]))
def test_invariants(units, l_max, order, saving, direction, marker):
    o = Options(l_max=l_max, l_min=1, cost="unit", order=order, saving_test=saving, direction=direction, marker_cost=marker, guard=False)
    got = fold_units(units, o)
    legend = {e.marker: e.units for e in got.legend}
    assert unfold_units(got.folded, legend) == units
    assert not any(u in legend for e in got.legend for u in e.units)
    taken = Counter(p for e in got.legend for s in e.starts for p in range(s, s + len(e.units)))
    assert not taken or max(taken.values()) == 1
    assert all(e.f >= 2 and (e.gain > 0 or not saving) for e in got.legend)
    assert got.n_tok - got.n_tok_folded - got.n_tok_legend == sum(e.gain for e in got.legend)
    assert got.n_tok_folded == len(got.folded)


@settings(max_examples=60, deadline=None)
@given(texts, st.integers(2, 6))
def test_folding_again_finds_nothing(units, l_max):
    first = fold_units(units, U(l_max=l_max, guard=False))
    own = {e.marker for e in first.legend}
    runs, run = [], []
    for u in first.folded:
        if u in own:
            runs.append(run)
            run = []
        else:
            run.append(u)
    runs.append(run)
    # Unique separators stand for the markers: nothing may repeat across or beside them.
    again = [x for i, r in enumerate(runs) for x in [*r, f"|{i}|"]]
    assert not fold_units(again, U(l_max=l_max, guard=False)).legend


def test_sweep_codes_once_and_ends_in_a_plateau():
    s = Shard((MIXED + " ") .split() * 3, "unit")
    rows = [s.fold(U(l_max=m)) for m in range(2, 40)]
    last = s.l_eff(39)
    assert all(r.folded == rows[last - 2].folded for r in rows[last - 2 :])


def test_records_and_guard():
    units = "a b c d a b c d".split()
    assert fold_units(units, U(l_max=4), [0, 4]).borders == [1]
    inside = fold_units("x a b y a b y a b y a b".split(), U(l_max=2, within_record=True), [0, 2, 5, 8, 11])
    assert all("y a" != " ".join(e.units) for e in inside.legend)
    bad = fold_units("a b c a b d".split(), U(l_max=2, saving_test=False))
    assert bad.guarded and bad.folded == "a b c a b d".split()
