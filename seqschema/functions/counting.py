"""Exact counts of words by length, and the precision measures built on them.

Symbols occur once, so words are counted without listing any: by length, concatenation convolves, interleaving
convolves with binomials, choice adds up with the empty word counted once.
"""

from __future__ import annotations

import functools
import math

from seqschema.functions.expr import Choice, Concat, Empty, Repeat, Shuffle, Symbol, children, parse_expr, symbols, words

#: Beyond this many symbols in a counted word, expressions that repeat symbols are not listed word by word.
LISTED = 8


def _vector(e, n: int, plain: bool) -> list[int]:
    """plain: count every symbol as occurring exactly once."""
    if isinstance(e, Empty):
        return [1] + [0] * n
    if isinstance(e, Symbol):
        return ([0, 1] + [0] * n)[: n + 1]
    if isinstance(e, Repeat):
        if plain:
            return _vector(e.part, n, plain)
        if isinstance(e.part, Symbol):
            return ([int(e.op in "?*"), 1] + [int(e.op in "*+")] * n)[: n + 1]
        if e.op == "?":
            return [1, *_vector(e.part, n, plain)[1:]]
        if isinstance(e.part, Choice) and all(isinstance(p, Symbol) for p in e.part.parts):
            k = len(e.part.parts)
            return [int(e.op == "*")] + [k**i for i in range(1, n + 1)]
        raise ValueError("repetition of a group has no exact count by length here")
    parts = [_vector(c, n, plain) for c in children(e)]
    if isinstance(e, Choice):
        total = [sum(x) for x in zip(*parts, strict=True)]
        return [min(1, total[0]), *total[1:]]
    out = [1] + [0] * n
    for v in parts:
        own = [(k, x) for k, x in enumerate(v) if x]
        out = [sum(out[i - k] * x * (math.comb(i, k) if isinstance(e, Shuffle) else 1) for k, x in own if k <= i) for i in range(n + 1)]
    return out


def default_length(e) -> int:
    return 2 * len(set(symbols(e))) + 1


@functools.lru_cache(maxsize=4096)
def word_counts(text: str, n: int | None = None) -> tuple[int, ...]:
    """Number of words of each length 0..n; n is twice the alphabet plus one unless given."""
    e = parse_expr(text)
    n = default_length(e) if n is None else n
    once = len(set(symbols(e))) == len(symbols(e))
    if once:
        try:
            return tuple(_vector(e, n, False))
        except ValueError:
            pass
    if n > LISTED:
        raise ValueError(f"{text!r}: words of up to {n} symbols cannot be counted without listing them")
    lengths = [len(w) for w in words(e, n)]
    return tuple(lengths.count(i) for i in range(n + 1))


def language_size(text: str, n: int | None = None) -> int:
    return sum(word_counts(text, n))


def shuffle_count(text: str) -> int:
    """Interleavings, when every symbol counts as occurring once and repetition marks are ignored."""
    e = parse_expr(text)
    return sum(_lengths_once(e, len(symbols(e))))


def _lengths_once(e, n: int) -> list[int]:
    """As _vector with plain symbols, but choices of equal words add up."""
    if isinstance(e, Repeat):
        return _lengths_once(e.part, n)
    if isinstance(e, Choice):
        return [sum(x) for x in zip(*(_lengths_once(p, n) for p in e.parts), strict=True)]
    if isinstance(e, Concat | Shuffle):
        out = [1] + [0] * n
        for v in (_lengths_once(p, n) for p in e.parts):
            out = [sum(out[i - k] * v[k] * (math.comb(i, k) if isinstance(e, Shuffle) else 1) for k in range(i + 1) if v[k]) for i in range(n + 1)]
        return out
    return _vector(e, n, True)


def log2_choose(n: int, k: int) -> float:
    """log2 of the binomial; infinite if more samples than words."""
    if k > n:
        return math.inf
    k = min(k, n - k)
    if k <= 4096:
        return math.fsum(math.log2(n - j) - math.log2(j + 1) for j in range(k))
    if n < 1 << 50:
        return (math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)) / math.log(2)
    return k * math.log2(n) - math.lgamma(k + 1) / math.log(2)


def data_cost(text: str, distinct_by_length: dict[int, int], n: int | None = None) -> float:
    """Bits to name the sample among the words of each length, from length one on. Longer samples are left out."""
    counts = word_counts(text, n)
    return math.fsum(2 * math.log2(i) + log2_choose(counts[i], distinct_by_length.get(i, 0)) for i in range(1, len(counts)))
