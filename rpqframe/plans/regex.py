"""Regular expressions over edge labels: syntax tree, parser, static facts, normalisation.

Postfix operators bind tighter than concatenation, concatenation tighter than alternation.
"""

from __future__ import annotations

import re
from dataclasses import dataclass


class Regex:
    pass


@dataclass(frozen=True)
class Lab(Regex):
    name: str

    def __str__(self):
        return self.name


@dataclass(frozen=True)
class Neg(Regex):
    name: str

    def __str__(self):
        return f"!{self.name}"


@dataclass(frozen=True)
class Cat(Regex):
    left: Regex
    right: Regex

    def __str__(self):
        return f"({self.left}.{self.right})"


@dataclass(frozen=True)
class Alt(Regex):
    left: Regex
    right: Regex

    def __str__(self):
        return f"({self.left}|{self.right})"


@dataclass(frozen=True)
class Plus(Regex):
    inner: Regex

    def __str__(self):
        return f"{self.inner}+"


@dataclass(frozen=True)
class Star(Regex):
    inner: Regex

    def __str__(self):
        return f"{self.inner}*"


@dataclass(frozen=True)
class Opt(Regex):
    inner: Regex

    def __str__(self):
        return f"{self.inner}?"


class ParseError(ValueError):
    pass


_TOKEN = re.compile(r"\s*([A-Za-z_][A-Za-z0-9_]*|[!.|+*?()])")


def parse_regex(text: str) -> Regex:
    tokens, at = [], 0
    while at < len(text.rstrip()):
        m = _TOKEN.match(text, at)
        if not m:
            raise ParseError(f"unexpected {text[at:at + 10]!r} in the path pattern")
        tokens.append(m[1])
        at = m.end()
    tokens.append("")

    def alternation() -> Regex:
        out = concatenation()
        while tokens[0] == "|":
            tokens.pop(0)
            out = Alt(out, concatenation())
        return out

    def concatenation() -> Regex:
        out = postfix()
        while tokens[0] == ".":
            tokens.pop(0)
            out = Cat(out, postfix())
        return out

    def postfix() -> Regex:
        out = atom()
        while tokens[0] in ("+", "*", "?"):
            out = {"+": Plus, "*": Star, "?": Opt}[tokens.pop(0)](out)
        return out

    def atom() -> Regex:
        t = tokens.pop(0)
        if t == "(":
            out = alternation()
            if tokens.pop(0) != ")":
                raise ParseError("a parenthesis is not closed")
            return out
        if t == "!":
            name = tokens.pop(0)
            if not name or not (name[0].isalpha() or name[0] == "_"):
                raise ParseError("a label must follow '!'")
            return Neg(name)
        if t and (t[0].isalpha() or t[0] == "_"):
            return Lab(t)
        raise ParseError(f"unexpected {t or 'end'!r} in the path pattern")

    out = alternation()
    if tokens != [""]:
        raise ParseError(f"unexpected {tokens[0]!r} in the path pattern")
    return out


def nullable(r: Regex) -> bool:
    if isinstance(r, (Star, Opt)):
        return True
    if isinstance(r, Plus):
        return nullable(r.inner)
    if isinstance(r, Cat):
        return nullable(r.left) and nullable(r.right)
    return isinstance(r, Alt) and (nullable(r.left) or nullable(r.right))


def first_labels(r: Regex) -> list[str]:
    """Labels an edge of a match can start with, in order; negations give nothing."""
    if isinstance(r, Lab):
        return [r.name]
    if isinstance(r, Alt):
        return list(dict.fromkeys(first_labels(r.left) + first_labels(r.right)))
    if isinstance(r, Cat):
        return list(dict.fromkeys(first_labels(r.left) + (first_labels(r.right) if nullable(r.left) else [])))
    return [] if isinstance(r, Neg) else first_labels(r.inner)


def lengths(r: Regex) -> tuple[int, int | None]:
    """Shortest and longest match; None: unbounded."""
    if isinstance(r, (Lab, Neg)):
        return 1, 1
    if isinstance(r, Cat):
        (a, b), (c, d) = lengths(r.left), lengths(r.right)
        return a + c, None if b is None or d is None else b + d
    if isinstance(r, Alt):
        (a, b), (c, d) = lengths(r.left), lengths(r.right)
        return min(a, c), None if b is None or d is None else max(b, d)
    a, b = lengths(r.inner)
    if isinstance(r, Opt):
        return 0, b
    return (0 if isinstance(r, Star) else a), (0 if b == 0 else None)


def uniform_len(r: Regex) -> int | None:
    a, b = lengths(r)
    return a if a == b else None


def labels_of(r: Regex) -> set[str]:
    if isinstance(r, (Lab, Neg)):
        return {r.name}
    if isinstance(r, (Cat, Alt)):
        return labels_of(r.left) | labels_of(r.right)
    return labels_of(r.inner)


def negates(r: Regex) -> bool:
    if isinstance(r, (Cat, Alt)):
        return negates(r.left) or negates(r.right)
    return isinstance(r, Neg) or not isinstance(r, Lab) and negates(r.inner)


def normalize(r: Regex) -> Regex:
    """The same set of words, without nested closures and options."""
    if isinstance(r, (Lab, Neg)):
        return r
    if isinstance(r, (Cat, Alt)):
        return type(r)(normalize(r.left), normalize(r.right))
    inner = normalize(r.inner)
    if isinstance(r, Plus):
        return inner if isinstance(inner, (Plus, Star)) else Star(inner.inner) if isinstance(inner, Opt) else Plus(inner)
    if isinstance(r, Star):
        return Star(inner.inner) if isinstance(inner, (Plus, Star, Opt)) else Star(inner)
    return inner if isinstance(inner, (Star, Opt)) else Star(inner.inner) if isinstance(inner, Plus) else Opt(inner)


def to_python(r: Regex, alphabet: list[str]) -> str:
    """The same language for Python's re, over labels that each end in a dot."""
    if isinstance(r, Lab):
        return re.escape(r.name + ".")
    if isinstance(r, Neg):
        return "(?:" + "|".join(re.escape(x + ".") for x in alphabet if x != r.name) + ")"
    if isinstance(r, Cat):
        return to_python(r.left, alphabet) + to_python(r.right, alphabet)
    if isinstance(r, Alt):
        return f"(?:{to_python(r.left, alphabet)}|{to_python(r.right, alphabet)})"
    return f"(?:{to_python(r.inner, alphabet)}){ {Plus: '+', Star: '*', Opt: '?'}[type(r)]}"
