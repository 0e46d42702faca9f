"""Worked examples, exact counts and properties of the graph stage and the measures."""

import random

import pytest

from seqschema.functions import classes, counting, expr, solver
from seqschema.functions.solver import LEARNERS, Summary

SAMPLE = ["aabcde", "acdcfe", "dbbcfe", "adbcef"]

#: Shapes with their shuffle counts and language sizes (three digits), recomputed exactly.
SHAPES = [
    ("a* & b* & c+ & d & e & f?", 720, 1.709e8), ("a* d e & b* c+ f?", 20, 1.787e5), ("a* (b* c+ & d) (e & f?)", 6, 4862),
    ("a1 a2+ a3 a4+ a5 a6* (a10* & a7*) a8 a9", 2, 261156), ("a1 a2+ a3 a4+ a5 a6* a7* a8 a9 & a10*", 10, 1.416e8),
    ("(a10* | a17? | a6?) & (a5* | a3? | a7?) & (a2* | a1*) & a14* & a15*", 2160, 1.434e15),
    ("a6? a1* a14* a5* a3? a7? a17? & a15* & a2* a10*", 360, 4.115e13), ("a1* a6? (a14* a5* & a15* & a2* a10* a3? a7? a17?)", 168, 1.108e13),
    ("a13? a20? & a12* a7* & a17+ a16? & a2+ a14 a9? a21* a15? & a11? a19* a10*", 15135120, 5.864e22),
    ("a2+ a14 (a19* & a13? a20? & a17+ a16? a11? & a21* a10* & a12* a9? a15? a7*)", 831600, 7.615e20),
    ("(a11? | a9? | a19*) & (a10* | a20? | a15?) & a7* & a16? & a12* & a13? & a2+ & a14 & a21* & a17+", 32659200, 4.798e26),
    ("a1 a2 (a3? & a4* & a5*) a7* a6* a8?", 6, 2.687e6), ("a3? & a4* & a1 a2 a5* a7* a6* a8?", 56, 1.131e8), ("(a6* | a7*) & a5* & a4* & a1 & a2 & a3? & a8?", 10080, 3.613e11),
]


def test_worked_example():
    s = Summary.of(SAMPLE)
    assert {a: s.op(a) for a in s.names} == {"a": "*", "b": "*", "c": "+", "d": "1", "e": "1", "f": "?"}
    both, one = solver.split_pairs(s.before)
    assert both == {("c", "d"), ("d", "c"), ("b", "d"), ("d", "b"), ("e", "f"), ("f", "e")} and len(one) == 12
    assert solver.components(s.names, both) == [["a"], ["b", "c", "d"], ["e", "f"]]
    assert {a + b for a, b in s.follows if a != solver.SOURCE and b != solver.SINK} == {"aa", "ab", "ac", "ad", "bb", "bc", "cd", "ce", "cf", "db", "dc", "de", "ef", "fe"}
    _, edges, _, _ = solver.grouped(s)
    assert edges == {(solver.SOURCE, "a"), (solver.SOURCE, "b"), ("a", "b"), ("b", "e"), ("e", solver.SINK)}
    assert solver.levels(edges) == {solver.SOURCE: 0, "a": 1, "b": 2, "e": 3, solver.SINK: 4} and solver.skipped_levels(edges, solver.levels(edges)) == {1}
    for mis in solver.INDEPENDENT:
        assert solver.level_chain(s, mis=mis)["expr"] == "a* (b* c+ & d) (e & f?)"
    assert solver.outer_shuffle(s, mis="exact")["expr"] == "a* b* c+ e & d f?"
    assert {a: Summary.of(["aabd", "abcd", "bbcd"]).op(a) for a in "abcd"} == {"a": "*", "b": "+", "c": "?", "d": "1"}


@pytest.mark.parametrize(("text", "shuffles", "size"), SHAPES)
def test_published_shapes(text, shuffles, size):
    assert counting.shuffle_count(text) == shuffles
    assert counting.language_size(text) == pytest.approx(size, rel=1e-3)


@pytest.mark.parametrize(("text", "cost"), [(SHAPES[0][0], 108.6705), (SHAPES[1][0], 92.4529), (SHAPES[2][0], 85.6647)])
def test_data_cost(text, cost):
    assert counting.data_cost(text, {6: 4}) == pytest.approx(cost, abs=1e-4)


def random_sample(rnd, n=5):
    return ["".join(rnd.choice("abcdef"[: rnd.randrange(2, 7)]) for _ in range(rnd.randrange(7))) for _ in range(rnd.randrange(1, n))]


def test_every_learner_accepts_its_sample_and_stays_in_its_class():
    rnd = random.Random(1)
    for _ in range(400):
        sample = random_sample(rnd)
        s = Summary.of(sample)
        if not s.present:
            continue
        for name, learn in LEARNERS.items():
            e = expr.parse_expr(learn(s)["expr"])
            assert all(expr.matches_general(w, e) for w in sample), (name, sample, expr.to_text(e))
            flags = classes.class_flags(e)
            want = {"level_chain": "level_chain", "outer_shuffle": "outer_shuffle", "all_shuffle": "plain_bag", "disjunctive_bag": "disjunctive_bag", "chain_factor": "chain_factor", "single_occurrence": "single_occurrence", "universal": "single_occurrence"}[name]
            assert flags[want], (name, sample, expr.to_text(e))
        for options in ({"mis": "exact"}, {"mis": "greedy"}, {"same_level": "choice"}, {"mark_groups": True}):
            e = expr.parse_expr(solver.level_chain(s, **options)["expr"])
            assert all(expr.matches_general(w, e) for w in sample), (options, sample, expr.to_text(e))
        least, repeated, greedy = (solver.disjunctive_bag(s, branch_ops="tight", cover=c) for c in ("exact", "repeated", "greedy"))
        assert all(expr.matches_general(w, expr.parse_expr(e["expr"])) for w in sample for e in (least, repeated, greedy))
        assert least["n_groups"] <= min(repeated["n_groups"], greedy["n_groups"])


def test_group_marks_change_nothing_and_sizes_are_ordered():
    rnd = random.Random(2)
    for _ in range(300):
        s = Summary.of(random_sample(rnd))
        if not s.present:
            continue
        plain, marked = (solver.level_chain(s, mark_groups=m)["expr"] for m in (False, True))
        assert counting.word_counts(plain) == counting.word_counts(marked)
        sizes = [counting.language_size(x["expr"]) for x in (solver.level_chain(s, mis="exact"), solver.outer_shuffle(s, mis="exact"), solver.all_shuffle(s))]
        assert sizes == sorted(sizes)


def test_cycles_are_repaired():
    for sample in (["xb", "by", "xy", "yx"], ["ab", "bc", "ca"], ["ab", "cd"], [""], ["", "a"]):
        e = expr.parse_expr(solver.level_chain(Summary.of(sample))["expr"])
        assert all(expr.matches_general(w, e) for w in sample)
    assert solver.level_chain(Summary.of(["ab", "cd"]), same_level="choice")["n_groups"] == 4


def test_counts_equal_listing():
    rnd = random.Random(3)
    for text in ["a* b+ & c", "(a | b?) c*", "a? & b? & c?", "(a & b)? c", "(a | b)* c?", "()", "a (b | c d)"]:
        listed = [len(w) for w in expr.words(expr.parse_expr(text), 6)]
        assert list(counting.word_counts(text, 6)) == [listed.count(i) for i in range(7)]
    assert expr.shuffle_words(("a",), ("b", "c")) == {tuple("abc"), tuple("bac"), tuple("bca")}
    for _ in range(200):
        e = expr.parse_expr(solver.level_chain(Summary.of(random_sample(rnd)))["expr"])
        for w in random_sample(rnd, 8):
            assert (tuple(w) in expr.words(e, 7)) == expr.matches_general(w, e)
        assert expr.parse_expr(expr.to_text(e)) == e and expr.canonical(e) == expr.canonical(expr.simplify(e))


def test_class_examples_and_lattice():
    flags = lambda t: {k for k, v in classes.class_flags(expr.parse_expr(t)).items() if v}
    assert {"outer_shuffle", "level_chain"} <= flags("a & b* c & d e?")
    assert "level_chain" in flags("a? (b c? & d+ e) f*") and "outer_shuffle" not in flags("a? (b c? & d+ e) f*")
    assert "disjunctive_bag" in flags("(a* | b?) & c") and "level_chain" not in flags("(a* | b?) & c")
    assert flags("a b a") == set() and "chain_factor" in flags("(a | b)+ c?") and "single_occurrence" in flags("((a b)* | c)")
    assert expr.positions(expr.parse_expr("a? b & c"))[0] == {"a", "b", "c"} and expr.expr_length(expr.parse_expr("a* b & c")) == 6
    for text in [s[0] for s in SHAPES]:
        f = flags(text)
        assert ("outer_shuffle" not in f or "level_chain" in f) and ("level_chain" not in f or "shuffle_single_occurrence" in f)
    assert expr.to_text(expr.parse_expr("'a b'* 'it\\'s' | ()")) == "'a b'* 'it\\'s' | ()"


def test_covers_are_exact_or_refused():
    alone = lambda n: Summary.of([[f"s{i}"] for i in range(n)])
    assert solver.disjunctive_bag(alone(16), cover="exact")["n_groups"] == solver.disjunctive_bag(alone(40), cover="repeated")["n_groups"] == 1
    for cover, n in (("exact", 17), ("repeated", 41)):
        with pytest.raises(ValueError, match="another cover"):
            solver.disjunctive_bag(alone(n), cover=cover)
        assert solver.disjunctive_bag(alone(n), cover="greedy")["n_groups"] >= 1


def test_seventy_symbols():
    names = [f"s{i}" for i in range(70)]
    s = Summary.of([names, names[::-1]])
    assert len(solver.level_chain(s)["groups"][0][0]) == 70 and solver.outer_shuffle(s)["n_groups"] == 1
