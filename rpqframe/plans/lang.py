"""The query language: MATCH [restrictor] p = (x)-[regex]->(y) [WHERE ...] RETURN ... [LIMIT n].

Without a restrictor the path semantics is WALK. Conditions on x are about the first node, on y
about the last; ``x.id`` is the node's id. The arrow may be written ``]->(y)`` or ``]-(y)``.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from rpqframe.functions.conditions import LENGTH, SEQ, And, Cmp, Is, Not, Or, Term, edge, label, node, prop
from rpqframe.functions.paths import LAST
from rpqframe.functions.restrictors import RESTRICTORS, WALK
from rpqframe.plans.regex import ParseError, Regex, parse_regex


@dataclass(frozen=True)
class Query:
    tau: str
    regex: Regex
    where: object | None
    returns: tuple[tuple[str, object], ...]
    limit: int
    path: str = "p"
    source: str = "x"
    target: str = "y"


_HEAD = re.compile(r"\s*MATCH\s+(?:(WALK|TRAIL|SIMPLE|ACYCLIC)\s+)?(\w+)\s*=\s*\(\s*(\w+)\s*\)\s*-\s*\[", re.I)
_WORDS = re.compile(r"""\s*("(?:[^"\\]|\\.)*"|'(?:[^'\\]|\\.)*'|-?\d+\.\d+|-?\d+|[A-Za-z_]\w*|<=|>=|!=|<>|[=<>().,+])""")


def parse(text: str) -> Query:
    m = _HEAD.match(text)
    if not m:
        raise ParseError("a query starts with MATCH [restrictor] p = (x)-[")
    depth, at = 1, m.end()
    while at < len(text) and depth:
        depth += {"[": 1, "]": -1}.get(text[at], 0)
        at += 1
    if depth:
        raise ParseError("the path pattern is not closed")
    tail = re.match(r"\s*->?\s*\(\s*(\w+)\s*\)", text[at:])
    if not tail:
        raise ParseError("a target node must follow the path pattern")
    tau, path, source, target = (m[1] or WALK).lower(), m[2], m[3], tail[1]
    assert tau in RESTRICTORS
    reader = _Reader(text[at + tail.end() :], path, source, target)
    where = reader.condition() if reader.word("WHERE") else None
    if not reader.word("RETURN"):
        raise ParseError("RETURN is missing")
    returns = reader.returns()
    limit = int(reader.take()) if reader.word("LIMIT") else 0
    if reader.tokens:
        raise ParseError(f"unexpected {reader.tokens[0]!r} at the end")
    return Query(tau, parse_regex(text[m.end() : at - 1]), where, tuple(returns), limit, path, source, target)


class _Reader:
    def __init__(self, text: str, path: str, source: str, target: str):
        self.tokens, at = [], 0
        text = text.rstrip().rstrip(";").rstrip()
        while at < len(text):
            m = _WORDS.match(text, at)
            if not m:
                raise ParseError(f"unexpected {text[at:at + 10]!r}")
            self.tokens.append(m[1])
            at = m.end()
        self.path, self.ends = path, {source: 1, target: LAST}

    def word(self, w: str) -> bool:
        if self.tokens and self.tokens[0].upper() == w:
            self.tokens.pop(0)
            return True
        return False

    def take(self) -> str:
        if not self.tokens:
            raise ParseError("the query ends too early")
        return self.tokens.pop(0)

    def expect(self, t: str) -> None:
        got = self.take()
        if got != t:
            raise ParseError(f"{t!r} expected, not {got!r}")

    def condition(self):
        out = self.conjunction()
        while self.word("OR"):
            out = Or(out, self.conjunction())
        return out

    def conjunction(self):
        out = self.negation()
        while self.word("AND"):
            out = And(out, self.negation())
        return out

    def negation(self):
        if self.word("NOT"):
            return Not(self.negation())
        if self.tokens[:1] == ["("]:
            self.take()
            out = self.condition()
            self.expect(")")
            return out
        return self.comparison()

    def comparison(self):
        t = self.term()
        if isinstance(t, Is):
            return t
        op = self.take()
        if op not in ("=", "!=", "<>", "<", "<=", ">", ">="):
            raise ParseError(f"a comparison expected, not {op!r}")
        return Cmp(t, "!=" if op == "<>" else op, self.value())

    def value(self):
        v = self.take()
        if v[0] in "\"'":
            return re.sub(r"\\(.)", r"\1", v[1:-1])
        if re.fullmatch(r"-?\d+", v):
            return int(v)
        if re.fullmatch(r"-?\d+\.\d+", v):
            return float(v)
        if v.lower() in ("true", "false"):
            return v.lower() == "true"
        raise ParseError(f"a value expected, not {v!r}")

    def position(self) -> int | str:
        v = self.take()
        if v.lower() in ("len", "length"):  # the last node is len()+1, the last edge len()
            self.expect("(")
            self.expect(")")
            if self.tokens[:1] == ["+"]:
                self.take()
                self.expect("1")
            elif self.tokens[:1] == ["+1"]:
                self.take()
            return LAST
        if not v.isdigit() or v == "0":
            raise ParseError(f"a position counts from 1, not {v!r}")
        return int(v)

    def term(self):
        name = self.take()
        low = name.lower()
        if name in self.ends:
            at = self.ends[name]
            if self.tokens[:1] != ["."]:
                return node(at)
            self.take()
            key = self.take()
            return node(at) if key == "id" else prop("node", at, key)
        if self.tokens[:1] != ["("]:
            if name == self.path:
                return SEQ
            raise ParseError(f"unknown name {name!r}")
        self.take()
        if low in ("istrail", "issimple", "isacyclic", "length", "len", "seq"):
            if self.tokens[:1] == [self.path]:
                self.take()
            self.expect(")")
            return {"length": LENGTH, "len": LENGTH, "seq": SEQ}.get(low) or Is(low[2:])
        if low in ("node", "edge"):
            i = self.position()
            self.expect(")")
            return node(i) if low == "node" else edge(i)
        if low in ("nlabel", "elabel"):
            i = self.position()
            self.expect(")")
            return label("node" if low[0] == "n" else "edge", i)
        if low in ("nprop", "eprop"):
            i = self.position()
            self.expect(",")
            key = self.take()
            self.expect(")")
            return prop("node" if low[0] == "n" else "edge", i, key.strip("\"'"))
        if low in ("label", "prop"):
            t = node(self.ends[self.take()]) if self.tokens and self.tokens[0] in self.ends else self.term()
            if not isinstance(t, Term) or t.kind != "id":
                raise ParseError(f"{low} needs a node or an edge")
            key = ""
            if low == "prop":
                self.expect(",")
                key = self.take().strip("\"'")
            self.expect(")")
            return label(t.what, t.i) if low == "label" else prop(t.what, t.i, key)
        raise ParseError(f"unknown function {name!r}")

    def returns(self) -> list[tuple[str, object]]:
        out = []
        while True:
            before = list(self.tokens)
            t = self.term()
            if isinstance(t, Term) and self.tokens[:1] and self.tokens[0] in ("=", "!=", "<>", "<", "<=", ">", ">="):
                op = self.take()
                t = Cmp(t, "!=" if op == "<>" else op, self.value())
            name = "".join(before[: len(before) - len(self.tokens)])
            if self.word("AS"):
                name = self.take()
            out.append((name, t))
            if self.tokens[:1] != [","]:
                return out
            self.take()
