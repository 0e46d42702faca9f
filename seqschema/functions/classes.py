"""Tests of the expression classes."""

from __future__ import annotations

from seqschema.functions.expr import Choice, Concat, Empty, Repeat, Shuffle, Symbol, children, simplify, symbols, to_groups

CLASSES = ("has_shuffle", "single_occurrence", "chain_factor", "shuffle_single_occurrence", "disjunctive_bag", "plain_bag", "outer_shuffle", "level_chain", "conflict_free")


def has_shuffle(e) -> bool:
    return isinstance(e, Shuffle) or any(map(has_shuffle, children(e)))


def once(e) -> bool:
    return len(symbols(e)) == len(set(symbols(e)))


def is_factor(e) -> bool:
    """A symbol or disjunction of symbols with at most one repetition mark."""
    body = e.part if isinstance(e, Repeat) else e
    return isinstance(body, Symbol) or (isinstance(body, Choice) and all(isinstance(p, Symbol) for p in body.parts))


def is_marked_symbol(e) -> bool:
    return isinstance(e, Symbol) or (isinstance(e, Repeat) and isinstance(e.part, Symbol))


def is_bag_part(e) -> bool:
    body = e.part if isinstance(e, Repeat) and not isinstance(e.part, Symbol) and e.op == "?" else e
    return is_marked_symbol(body) or (isinstance(body, Choice) and all(map(is_marked_symbol, body.parts)))


def repeats_symbols_only(e) -> bool:
    if isinstance(e, Repeat) and e.op in "*+" and not isinstance(e.part, Symbol):
        return False
    return all(map(repeats_symbols_only, children(e)))


def class_flags(e) -> dict[str, bool]:
    e = simplify(e)
    single, shuffled = once(e), has_shuffle(e)
    top = e.parts if isinstance(e, Shuffle) else (e,)
    chain = lambda p: all(map(is_marked_symbol, p.parts if isinstance(p, Concat) else (p,)))
    return {
        "has_shuffle": shuffled,
        "single_occurrence": single and not shuffled,
        "chain_factor": single and not shuffled and all(map(is_factor, e.parts if isinstance(e, Concat) else () if isinstance(e, Empty) else (e,))),
        "shuffle_single_occurrence": single,
        "disjunctive_bag": single and (isinstance(e, Empty) or all(map(is_bag_part, top))),
        "plain_bag": single and (isinstance(e, Empty) or all(map(is_marked_symbol, top))),
        "outer_shuffle": single and (isinstance(e, Empty) or all(map(chain, top))),
        "level_chain": single and to_groups(e) is not None,
        "conflict_free": single and repeats_symbols_only(e),
    }
