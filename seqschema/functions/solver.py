"""The graph stage: from one model's summary to its expression, by all learners.

A summary holds what the sample's strings have in common: for each symbol in how many strings it occurs and how often
at most, which symbol comes somewhere before which, and which follows directly. Sets of symbols are bit masks over the
sorted alphabet, so the lowest bit is the smallest name and every tie falls to it.
"""

from __future__ import annotations

import functools
import heapq
from collections.abc import Iterator
from dataclasses import dataclass, field

from seqschema.functions.expr import Choice, Concat, Repeat, Shuffle, Symbol, from_groups, joined, to_text

SOURCE, SINK = "⊢", "⊣"


@dataclass
class Summary:
    strings: int = 0  # distinct strings, the empty one included
    weight: int = 0  # strings, duplicates included
    present: dict[str, int] = field(default_factory=dict)
    most: dict[str, int] = field(default_factory=dict)
    before: set[tuple[str, str]] = field(default_factory=set)
    follows: set[tuple[str, str]] = field(default_factory=set)

    @classmethod
    def of(cls, strings) -> Summary:
        """Of literal strings (sequences of symbols)."""
        out, seen = cls(), list(strings)
        distinct = set(map(tuple, seen))
        out.weight, out.strings = len(seen), len(distinct)
        for s in distinct:
            for a in set(s):
                out.present[a] = out.present.get(a, 0) + 1
                out.most[a] = max(out.most.get(a, 0), s.count(a))
            out.before |= {(a, b) for i, a in enumerate(s) for b in s[i + 1 :] if a != b}
            out.follows |= set(zip((SOURCE, *s), (*s, SINK), strict=True))
        return out

    @property
    def names(self) -> list[str]:
        return sorted(self.present)

    def op(self, a: str) -> str:
        return {(True, False): "?", (True, True): "*", (False, False): "1", (False, True): "+"}[self.present[a] < self.strings, self.most[a] > 1]


def bits(mask: int) -> Iterator[int]:
    while mask:
        low = mask & -mask
        yield low.bit_length() - 1
        mask ^= low


def neighbours(names: list[str], pairs) -> list[int]:
    at, near = {a: i for i, a in enumerate(names)}, [0] * len(names)
    for a, b in pairs:
        near[at[a]] |= 1 << at[b]
        near[at[b]] |= 1 << at[a]
    return near


def ramsey(near: list[int], nodes: int) -> tuple[int, int]:
    """A clique and an independent set, by splitting on the smallest node's neighbours; with a stack of its own, so that
    large graphs need no deep recursion."""
    done: list[tuple[int, int]] = []
    todo: list[tuple[str, int]] = [("split", nodes)]
    while todo:
        what, mask = todo.pop()
        if what == "split":
            if not mask:
                done.append((0, 0))
                continue
            low = mask & -mask
            adjacent = near[low.bit_length() - 1]
            todo += [("join", low), ("split", mask & ~adjacent & ~low), ("split", mask & adjacent)]
        else:
            (c2, i2), (c1, i1) = done.pop(), done.pop()
            c1, i2 = c1 | mask, i2 | mask
            done.append((c1 if c1.bit_count() >= c2.bit_count() else c2, i2 if i2.bit_count() >= i1.bit_count() else i1))
    return done[0]


def set_by_ramsey(near: list[int], nodes: int) -> int:
    """Take out one clique after the other and keep the largest independent set met."""
    best = 0
    while nodes:
        clique, independent = ramsey(near, nodes)
        if independent.bit_count() > best.bit_count():
            best = independent
        nodes &= ~clique
    return best


def set_exact(near: list[int], nodes: int) -> int:
    @functools.cache
    def size(mask: int) -> int:
        if not mask:
            return 0
        v = max(bits(mask), key=lambda x: (near[x] & mask).bit_count())
        if not near[v] & mask:
            return mask.bit_count()
        return max(size(mask & ~(1 << v)), 1 + size(mask & ~near[v] & ~(1 << v)))

    out = 0
    while nodes:
        for v in bits(nodes):
            rest = nodes & ~near[v] & ~(1 << v)
            if size(rest) + 1 == size(nodes):
                out |= 1 << v
                nodes = rest
                break
    return out


def set_greedy(near: list[int], nodes: int) -> int:
    out = 0
    while nodes:
        v = min(bits(nodes), key=lambda x: (near[x] & nodes).bit_count())
        out |= 1 << v
        nodes &= ~near[v] & ~(1 << v)
    return out


INDEPENDENT = {"ramsey": set_by_ramsey, "exact": set_exact, "greedy": set_greedy}


def independent_partition(near: list[int], nodes: int, mis: str = "ramsey") -> list[int]:
    out = []
    while nodes:
        chosen = INDEPENDENT[mis](near, nodes)
        out.append(chosen)
        nodes &= ~chosen
    return out


def chain_order(names: list[str], one_way: set[tuple[str, str]]) -> tuple[list[str], list[str]]:
    """A chain in the order of the one-way pairs, ties by name, and the symbols left over: those that would close a cycle."""
    after = {a: {b for x, b in one_way if x == a} for a in names}
    inside: list[str] = []
    left: list[str] = []

    def reaches(start: str, goal: str) -> bool:
        seen, todo = set(), [start]
        while todo:
            x = todo.pop()
            if x == goal:
                return True
            for y in after[x] & set(inside) - seen:
                seen.add(y)
                todo.append(y)
        return False

    for a in names:
        inside.append(a)
        if any(reaches(b, a) for b in after[a] & set(inside)):
            inside.remove(a)
            left.append(a)
    waits = {a: sum(a in after[b] for b in inside) for a in inside}
    heap, out = sorted(a for a, n in waits.items() if not n), []
    while heap:
        a = heapq.heappop(heap)
        out.append(a)
        for b in after[a]:
            if b in waits:
                waits[b] -= 1
                if not waits[b]:
                    heapq.heappush(heap, b)
    return out, left


def split_pairs(before: set[tuple[str, str]]) -> tuple[set, set]:
    """Pairs seen in both orders, and in one order only."""
    both = {(a, b) for a, b in before if (b, a) in before}
    return both, before - both


def chains_of(nodes: list[str], before: set, mis: str) -> tuple[list[list[str]], int]:
    """Chains that partition a set of symbols, sorted by their least symbol; and how many symbols were put back."""
    both, one_way = split_pairs(before)
    names, out, repairs = sorted(nodes), [], 0
    while names:
        keep = set(names)
        near = neighbours(names, [(a, b) for a, b in both if a in keep and b in keep])
        rest: list[str] = []
        for mask in independent_partition(near, (1 << len(names)) - 1, mis):
            own = [names[i] for i in bits(mask)]
            inner = {(a, b) for a, b in one_way if a in own and b in own}
            chain, left = chain_order(own, inner)
            out.append(chain)
            rest += left
        repairs += len(rest)
        names = sorted(rest)
    return sorted(out, key=min), repairs


def components(names: list[str], pairs) -> list[list[str]]:
    root = {a: a for a in names}

    def find(a: str) -> str:
        while root[a] != a:
            root[a] = root[root[a]]
            a = root[a]
        return a

    for a, b in pairs:
        x, y = sorted((find(a), find(b)))
        root[y] = x
    out: dict[str, list[str]] = {}
    for a in sorted(names):
        out.setdefault(find(a), []).append(a)
    return list(out.values())


def strongly_connected(nodes: list, edges: set) -> list[list]:
    """Sets of nodes that reach each other, by transitive closure on bit masks."""
    at = {x: i for i, x in enumerate(nodes)}
    reach = [1 << i for i in range(len(nodes))]
    for a, b in edges:
        reach[at[a]] |= 1 << at[b]
    for k in range(len(nodes)):
        for i in range(len(nodes)):
            if reach[i] >> k & 1:
                reach[i] |= reach[k]
    out, seen = [], 0
    for i, x in enumerate(nodes):
        if not seen >> i & 1:
            own = [j for j in bits(reach[i]) if reach[j] >> i & 1]
            seen |= sum(1 << j for j in own)
            out.append([nodes[j] for j in own])
    return out


def contract(follows: set, part_of: dict) -> set:
    """Edges between parts, loops dropped."""
    return {(part_of[a], part_of[b]) for a, b in follows if part_of[a] != part_of[b]}


def levels(edges: set, source=SOURCE) -> dict:
    """Length of the longest path from the source to each node of an acyclic graph."""
    after: dict = {}
    waits: dict = {source: 0}
    for a, b in edges:
        after.setdefault(a, []).append(b)
        waits[b] = waits.get(b, 0) + 1
        waits.setdefault(a, 0)
    out, ready = {x: 0 for x in waits}, [x for x, n in waits.items() if not n]
    while ready:
        a = ready.pop()
        for b in after.get(a, ()):
            out[b] = max(out[b], out[a] + 1)
            waits[b] -= 1
            if not waits[b]:
                ready.append(b)
    return out


def skipped_levels(edges: set, level: dict) -> set[int]:
    return {k for a, b in edges for k in range(level[a] + 1, level[b])}


def grouped(s: Summary) -> tuple[list[list[str]], set, dict[str, str], int]:
    """Parts of the alphabet whose quotient automaton is acyclic: components of the conflict graph, then merged where
    the quotient has cycles. Gives parts, quotient edges, the part (least symbol) of each symbol, and the merges."""
    both, _ = split_pairs(s.before)
    parts = components(s.names, both)
    part_of = {a: p[0] for p in parts for a in p} | {SOURCE: SOURCE, SINK: SINK}
    edges, repairs = contract(s.follows, part_of), 0
    merged = strongly_connected([p[0] for p in parts], {(a, b) for a, b in edges if a != SOURCE and b != SINK})
    if any(len(m) > 1 for m in merged):
        by_name = {p[0]: p for p in parts}
        parts = [sorted(a for x in m for a in by_name[x]) for m in merged]
        repairs = sum(len(m) - 1 for m in merged)
        part_of = {a: p[0] for p in parts for a in p} | {SOURCE: SOURCE, SINK: SINK}
        edges = contract(s.follows, part_of)
    return parts, edges, part_of, repairs


def level_chain(s: Summary, mis: str = "ramsey", mark_groups: bool = False, same_level: str = "concat") -> dict:
    parts, edges, _, repairs = grouped(s)
    level = levels(edges)
    skips, placed = skipped_levels(edges, level), []
    for p in parts:
        chains, put_back = chains_of(p, {(a, b) for a, b in s.before if a in p and b in p}, mis)
        repairs += put_back
        placed.append((level[p[0]], p[0], [[(a, s.op(a)) for a in c] for c in chains]))
    placed.sort(key=lambda x: x[:2])
    shuffled = [k for k, _, chains in placed if len(chains) > 1]
    groups = [(chains, mark_groups and len(chains) > 1 and (k in skips or shuffled.count(k) > 1)) for k, _, chains in placed]
    e = from_groups(groups)
    if same_level == "choice":
        out = []
        for k in sorted({x[0] for x in placed}):
            alike = [from_groups([g]) for x, g in zip(placed, groups, strict=True) if x[0] == k]
            whole = joined(Choice, alike)
            out.append(Repeat(whole, "?") if len(alike) > 1 and k in skips else whole)
        e = joined(Concat, out)
    return {"expr": to_text(e), "groups": groups if same_level == "concat" else None, "n_groups": len(groups), "n_repairs": repairs}


def outer_shuffle(s: Summary, mis: str = "ramsey") -> dict:
    chains, repairs = chains_of(s.names, s.before, mis)
    groups = [([[(a, s.op(a)) for a in c] for c in chains], False)] if chains else []
    return {"expr": to_text(from_groups(groups)), "groups": groups, "n_groups": len(groups), "n_repairs": repairs}


def marked(a: str, op: str):
    return Symbol(a) if op == "1" else Repeat(Symbol(a), op)


def all_shuffle(s: Summary) -> dict:
    groups = [([[(a, s.op(a))] for a in s.names], False)] if s.names else []
    return {"expr": to_text(from_groups(groups)), "groups": groups, "n_groups": len(groups), "n_repairs": 0}


#: The most symbols that each way of covering takes.
COVERED = {"exact": 16, "repeated": 40, "greedy": float("inf")}


def disjunctive_bag(s: Summary, branch_ops: str = "global", cover: str = "greedy") -> dict:
    """Symbols that never share a string become branches of one disjunction; disjunctions are interleaved. cover: how the
    symbols are dealt to disjunctions. exact: the fewest that hold all; repeated: a largest independent set, then one of
    the rest, and so on; greedy: the same with approximate sets. Beyond its bound an exact way is an error."""
    names = s.names
    if len(names) > COVERED[cover]:
        raise ValueError(f"cover={cover!r} takes at most {COVERED[cover]} symbols, not {len(names)}: use another cover")
    near = neighbours(names, s.before)
    masks = _least_cover(near, len(names)) if cover == "exact" else independent_partition(near, (1 << len(names)) - 1, "ramsey" if cover == "greedy" else "exact")
    parts = []
    for own in sorted([names[i] for i in bits(m)] for m in masks):
        if len(own) == 1 or branch_ops == "global":
            parts.append(joined(Choice, [marked(a, s.op(a)) for a in own]))
        else:
            whole = joined(Choice, [marked(a, "+" if s.most[a] > 1 else "1") for a in own])
            parts.append(whole if sum(s.present[a] for a in own) == s.strings else Repeat(whole, "?"))
    return {"expr": to_text(joined(Shuffle, parts)), "groups": None, "n_groups": len(parts), "n_repairs": 0}


def _least_cover(near: list[int], n: int) -> list[int]:
    """The fewest independent sets that cover all nodes; first found in order of names."""

    @functools.cache
    def cover(mask: int) -> tuple[int, ...]:
        if not mask:
            return ()
        low = mask & -mask
        best: tuple[int, ...] | None = None

        def grow(own: int, open_: int) -> None:
            nonlocal best
            if not open_:
                rest = cover(mask & ~own)
                if best is None or len(rest) + 1 < len(best):
                    best = (own, *rest)
                return
            v = open_ & -open_
            grow(own | v, open_ & ~near[v.bit_length() - 1] & ~v)
            if near[v.bit_length() - 1] & open_:
                grow(own, open_ & ~v)

        grow(low, mask & ~near[low.bit_length() - 1] & ~low)
        return best

    return list(cover((1 << n) - 1))


def chain_factor(s: Summary) -> dict:
    """Without interleaving: symbols that reach each other collapse into a repeated disjunction, levels follow each other."""
    names = s.names
    inner = {(a, b) for a, b in s.follows if a != SOURCE and b != SINK}
    parts = strongly_connected(names, inner)
    part_of = {a: p[0] for p in parts for a in p} | {SOURCE: SOURCE, SINK: SINK}
    edges = contract(s.follows, part_of)
    level = levels(edges)
    skips, out = skipped_levels(edges, level), []
    for k in range(1, max(level.values(), default=0) + 1):
        own = sorted(p for p in parts if level.get(p[0]) == k)
        plain = [p[0] for p in own if len(p) == 1 and (p[0], p[0]) not in inner]
        loops = [p for p in own if len(p) > 1 or (p[0], p[0]) in inner]
        several = len(loops) + bool(plain) > 1
        factors = ([(plain, "?" if several or k in skips else "1")] if plain else []) + [(p, "*" if several or k in skips else "+") for p in loops]
        for symbols, op in sorted(factors):
            body = joined(Choice, map(Symbol, symbols))
            out.append(body if op == "1" else Repeat(body, op))
    return {"expr": to_text(joined(Concat, out)), "groups": None, "n_groups": len(out), "n_repairs": 0}


def single_occurrence(s: Summary) -> dict:
    """Without interleaving: rewrite the automaton by disjunction, concatenation, repetition and option until one node is
    left; where no rule applies, the two nodes that reach each other (else the first two of a level) become a repeated
    disjunction, which accepts more."""
    label = {a: Symbol(a) for a in s.names}
    edges = {(a, b) for a, b in s.follows}
    repairs = 0

    def rename(new: str, old: set) -> None:
        nonlocal edges
        edges = {(new if a in old else a, new if b in old else b) for a, b in edges}

    while len(label) > 1 or any(a == b for a, b in edges) or ((SOURCE, SINK) in edges and label):
        into = {x: {a for a, b in edges if b == x and a != x} for x in label}
        out = {x: {b for a, b in edges if a == x and b != x} for x in label}
        loop = next((x for x in sorted(label) if (x, x) in edges), None)
        if loop is not None:
            edges.discard((loop, loop))
            label[loop] = Repeat(label[loop], "+")
            continue
        alike = next(((x, y) for x in sorted(label) for y in sorted(label) if x < y and into[x] == into[y] and out[x] == out[y]), None)
        if alike:
            x, y = alike
            label[x] = joined(Choice, [p for z in (label[x], label.pop(y)) for p in (z.parts if isinstance(z, Choice) else (z,))])
            rename(x, {y})
            continue
        row = next(((x, y) for x in sorted(label) for y in sorted(label) if x != y and out[x] == {y} and into[y] == {x}), None)
        if row:
            x, y = row
            edges.discard((x, y))
            label[x] = joined(Concat, [p for z in (label[x], label.pop(y)) for p in (z.parts if isinstance(z, Concat) else (z,))])
            rename(x, {y})
            continue
        bypass = next((x for x in sorted(label) if into[x] and out[x] and all((a, b) in edges for a in into[x] for b in out[x])), None)
        if bypass is not None:
            edges -= {(a, b) for a in into[bypass] for b in out[bypass]}
            label[bypass] = Repeat(label[bypass], "?")
            continue
        cyclic = [p for p in strongly_connected(sorted(label), {(a, b) for a, b in edges if a in label and b in label}) if len(p) > 1]
        if cyclic:
            own = cyclic[0]
        else:
            depth = levels(edges)
            own = next((sorted(x for x in label if depth.get(x) == k)[:2] for k in range(1, len(label) + 1) if sum(depth.get(x) == k for x in label) > 1), sorted(label, key=lambda x: (depth.get(x, 0), x))[:2])
        x, repairs = min(own), repairs + 1
        label[x] = joined(Choice, [p for z in own for p in (label[z].parts if isinstance(label[z], Choice) else (label[z],))])
        for z in own:
            if z != x:
                del label[z]
        rename(x, set(own))
        edges.add((x, x))
    e = next(iter(label.values())) if label else joined(Concat, [])
    from seqschema.functions.expr import simplify

    return {"expr": to_text(simplify(e)), "groups": None, "n_groups": 1 if label else 0, "n_repairs": repairs}


def universal(s: Summary) -> dict:
    e = Repeat(joined(Choice, map(Symbol, s.names)), "*") if s.names else joined(Concat, [])
    return {"expr": to_text(e), "groups": None, "n_groups": int(bool(s.names)), "n_repairs": 0}


LEARNERS = {
    "level_chain": level_chain, "outer_shuffle": outer_shuffle, "disjunctive_bag": disjunctive_bag, "all_shuffle": all_shuffle,
    "chain_factor": chain_factor, "single_occurrence": single_occurrence, "universal": universal,
}
