"""Automata of label expressions: positions, subset construction, ambiguity."""

from __future__ import annotations

from dataclasses import dataclass

from rpqframe.plans.regex import Alt, Cat, Lab, Neg, Opt, Plus, Regex, Star, nullable


@dataclass(frozen=True)
class Positions:
    """State 0 is the start; state k > 0 has just read the label at position k."""

    symbols: tuple[Regex, ...]
    first: frozenset[int]
    last: frozenset[int]
    follow: dict[int, frozenset[int]]
    empty: bool


def positions(r: Regex) -> Positions:
    symbols: list[Regex] = []
    follow: dict[int, set[int]] = {}

    def walk(x: Regex) -> tuple[set[int], set[int]]:
        if isinstance(x, (Lab, Neg)):
            symbols.append(x)
            k = len(symbols)
            follow[k] = set()
            return {k}, {k}
        if isinstance(x, Alt):
            (f1, l1), (f2, l2) = walk(x.left), walk(x.right)
            return f1 | f2, l1 | l2
        if isinstance(x, Cat):
            (f1, l1), (f2, l2) = walk(x.left), walk(x.right)
            for p in l1:
                follow[p] |= f2
            return f1 | (f2 if nullable(x.left) else set()), l2 | (l1 if nullable(x.right) else set())
        f, l = walk(x.inner)
        if isinstance(x, (Plus, Star)):
            for p in l:
                follow[p] |= f
        assert isinstance(x, (Plus, Star, Opt))
        return f, l

    f, l = walk(r)
    return Positions(tuple(symbols), frozenset(f), frozenset(l), {k: frozenset(v) for k, v in follow.items()}, nullable(r))


def reads(symbol: Regex, label: str) -> bool:
    return (symbol.name == label) == isinstance(symbol, Lab)


@dataclass(frozen=True)
class Dfa:
    """Deterministic, so each path has one run; state 0 is the start."""

    moves: dict[tuple[int, str], int]
    finals: frozenset[int]

    def states(self) -> int:
        return 1 + max([0, *self.moves.values()])

    def rows(self) -> list[tuple[int, str, int]]:
        return sorted((s, x, n) for (s, x), n in self.moves.items())


def compile_dfa(r: Regex, alphabet: list[str]) -> Dfa:
    """Subset construction over the graph's labels; ``!a`` reads every label but a."""
    p = positions(r)
    names: dict[frozenset[int], int] = {frozenset([0]): 0}
    todo, moves, finals = [frozenset([0])], {}, set()
    while todo:
        state = todo.pop()
        if state & p.last or 0 in state and p.empty:
            finals.add(names[state])
        for x in alphabet:
            to = frozenset(q for s in state for q in (p.first if s == 0 else p.follow[s]) if reads(p.symbols[q - 1], x))
            if to:
                if to not in names:
                    names[to] = len(names)
                    todo.append(to)
                moves[names[state], x] = names[to]
    return Dfa(moves, frozenset(finals))


def is_unambiguous(r: Regex, alphabet: list[str]) -> bool:
    """Whether every word matches in one way: no two different runs of the position automaton read it."""
    p = positions(r)
    start = (0, 0)
    nxt = lambda s: p.first if s == 0 else p.follow[s]
    seen, todo, back = {start}, [start], {}
    while todo:
        a, b = todo.pop()
        for q in nxt(a):
            for w in nxt(b):
                if any(reads(p.symbols[q - 1], x) and reads(p.symbols[w - 1], x) for x in alphabet):
                    back.setdefault((q, w), set()).add((a, b))
                    if (q, w) not in seen:
                        seen.add((q, w))
                        todo.append((q, w))
    ends = [(a, b) for a, b in seen if a in p.last and b in p.last]
    live, todo = set(ends), list(ends)
    while todo:
        for before in back.get(todo.pop(), ()):
            if before not in live:
                live.add(before)
                todo.append(before)
    return not any(a != b for a, b in live)
