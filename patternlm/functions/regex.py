"""A small regular-expression language: literals, classes, `.`, groups, alternation, `* + ? {m,n}`, escapes.

parse() gives a tree of tuples: ("lit", chars) one character of a set, ("cat", parts), ("alt", parts), ("rep", part, least, most or None).
Negated classes and `.` range over the alphabet given (printable ASCII by default). No look-around, back-references or anchors.
"""

from __future__ import annotations

from functools import lru_cache

ALPHABET = "".join(map(chr, range(32, 127)))
DIGITS = "0123456789"
LETTERS = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ"
CLASSES = {"d": DIGITS, "w": LETTERS + DIGITS + "_", "s": " \t\n\r\f\v"}
CONTROL = {"n": "\n", "t": "\t", "r": "\r"}
SPECIAL = set("\\.[](){}|*+?^$")


class RegexError(ValueError):
    pass


class _Reader:
    def __init__(self, text: str, alphabet: str):
        self.text, self.at, self.alphabet = text, 0, alphabet

    def peek(self) -> str:
        return self.text[self.at] if self.at < len(self.text) else ""

    def take(self, expected: str = "") -> str:
        c = self.peek()
        if not c or (expected and c != expected):
            raise RegexError(f"expected {expected or 'a character'} at {self.at} in {self.text!r}")
        self.at += 1
        return c

    def alternation(self):
        parts = [self.sequence()]
        while self.peek() == "|":
            self.take()
            parts.append(self.sequence())
        return parts[0] if len(parts) == 1 else ("alt", parts)

    def sequence(self):
        parts = []
        while self.peek() and self.peek() not in "|)":
            parts.append(self.repeated())
        return parts[0] if len(parts) == 1 else ("cat", parts)

    def repeated(self):
        part = self.atom()
        while self.peek() and self.peek() in "*+?{":
            c = self.take()
            if c == "{":
                body = ""
                while self.peek() != "}":
                    body += self.take()
                self.take("}")
                low, _, high = body.partition(",")
                part = ("rep", part, int(low or 0), int(high) if high else None if "," in body else int(low))
            else:
                part = ("rep", part, int(c == "+"), 1 if c == "?" else None)
        return part

    def atom(self):
        c = self.take()
        if c == "(":
            if self.text.startswith("?:", self.at):
                self.at += 2
            inner = self.alternation()
            self.take(")")
            return inner
        if c == "[":
            return ("lit", self.set_of())
        if c == ".":
            return ("lit", "".join(x for x in self.alphabet if x != "\n"))
        if c == "\\":
            return ("lit", self.escaped())
        if c in SPECIAL:
            raise RegexError(f"unexpected {c} at {self.at - 1} in {self.text!r}")
        return ("lit", c)

    def escaped(self) -> str:
        c = self.take()
        if c.lower() in CLASSES and c.isalpha():
            inside = CLASSES[c.lower()]
            return inside if c.islower() else "".join(x for x in self.alphabet if x not in inside)
        return CONTROL.get(c, c)

    def set_of(self) -> str:
        negated = self.peek() == "^"
        if negated:
            self.take()
        found: list[str] = []
        first = True
        while first or self.peek() != "]":
            first = False
            c = self.take()
            here = self.escaped() if c == "\\" else c
            if self.peek() == "-" and self.text[self.at + 1 : self.at + 2] not in ("]", "") and len(here) == 1:
                self.take()
                end = self.take()
                end = self.escaped() if end == "\\" else end
                here = "".join(map(chr, range(ord(here), ord(end) + 1)))
            found.append(here)
        self.take("]")
        inside = "".join(dict.fromkeys("".join(found)))
        return "".join(x for x in self.alphabet if x not in inside) if negated else inside


@lru_cache(maxsize=4096)
def parse(pattern: str, alphabet: str = ALPHABET):
    reader = _Reader(pattern, alphabet)
    tree = reader.alternation()
    if reader.peek():
        raise RegexError(f"unbalanced ) at {reader.at} in {pattern!r}")
    return tree


def escape(text: str) -> str:
    return "".join("\\" + c if c in SPECIAL else c for c in text)


def unescaped(pattern: str) -> str | None:
    """The one text that a pattern without operators stands for, or None."""
    out, at = [], 0
    while at < len(pattern):
        c = pattern[at]
        if c == "\\":
            at += 1
            c = pattern[at : at + 1]
            if c not in SPECIAL or not c:
                return None
        elif c in SPECIAL:
            return None
        out.append(c)
        at += 1
    return "".join(out)


def required_literals(tree) -> str:
    """A longest literal that every string of the language contains ('' if none is certain): a cheap filter before the regex."""
    best, run = "", ""

    def flat(t):
        return t[1] if t[0] == "cat" else [t]

    for part in flat(tree):
        while part[0] == "rep" and part[2] >= 1 and part[3] == part[2] == 1:
            part = part[1]
        if part[0] == "lit" and len(part[1]) == 1:
            run += part[1]
        else:
            run = required_literals(part) if part[0] == "cat" else ""
        best = max(best, run, key=len)
        if part[0] != "lit":
            run = ""
    return best
