"""Terms of texts and Boolean keyword expressions in disjunctive form.

An expression is an array of clauses, each a sorted array of distinct terms; a text satisfies it if it
has all terms of some clause.
"""

from __future__ import annotations

import re
from itertools import product

from pyspark.sql import Column
from pyspark.sql import functions as F

MAX_CLAUSES = 64
_LEX = re.compile(r"\s*(\(|\)|[^\s()]+)")


def tokens(text: Column) -> Column:
    """Runs of letters of at least two, lower-cased, in order; empty for null."""
    found = F.filter(F.split(F.lower(text), r"[^\p{L}]+"), lambda t: F.length(t) > 1)
    return F.coalesce(found, F.array().cast("array<string>"))


def distinct(terms: Column) -> Column:
    return F.array_sort(F.array_distinct(terms))


def matches(terms: Column, dnf: Column) -> Column:
    """Whether an array of terms satisfies an expression."""
    return F.exists(dnf, lambda clause: F.forall(clause, lambda t: F.array_contains(terms, t)))


def signature(terms: Column) -> Column:
    """64 bits, one set for each term by its hash: small enough to travel where terms are too long."""
    bit = lambda t: F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod(F.xxhash64(t), F.lit(64)).cast("int"))
    return F.aggregate(terms, F.lit(0).cast("long"), lambda bits, t: bits.bitwiseOR(bit(t)))


def code(term: Column) -> Column:
    return F.xxhash64(term)


def codes(terms: Column) -> Column:
    """A 64-bit code for each term, for short texts: with no two words of one code, they tell exactly what matches."""
    return F.transform(terms, code)


def first_match(found: Column, keys: Column) -> Column:
    """Place, from 0, of the first clause that a text with the codes ``found`` satisfies; -1 if none. ``keys`` are the clauses' codes."""
    return F.array_position(F.transform(keys, lambda clause: F.forall(clause, lambda k: F.array_contains(found, k))), True) - 1


def can_match(bits: Column, masks: Column) -> Column:
    """Whether terms with the signature ``bits`` can satisfy an expression whose clauses have ``masks``; never false
    where they do."""
    return F.exists(masks, lambda m: m.bitwiseAND(bits) == m)


def alive(reg_seq: Column, cancel_seq: Column, seq: Column) -> Column:
    """Whether a subscription is registered, and not cancelled, when the tuple ``seq`` comes."""
    return (reg_seq < seq) & (cancel_seq.isNull() | (seq < cancel_seq))


def to_dnf(expression: str) -> list[list[str]]:
    """Clauses of an expression of words, AND, OR and parentheses. AND binds closer; case of words is dropped.

    Distribution can multiply clauses; over ``MAX_CLAUSES`` is an error. Repeated terms, equal clauses and
    clauses that another one implies are removed.
    """
    words = _LEX.findall(expression)
    at = 0

    def peek() -> str | None:
        return words[at] if at < len(words) else None

    def take() -> str:
        nonlocal at
        at += 1
        return words[at - 1]

    def either() -> list[frozenset[str]]:
        out = both()
        while (peek() or "").upper() == "OR":
            take()
            out = out + both()
        return out

    def both() -> list[frozenset[str]]:
        out = one()
        while (peek() or "").upper() == "AND":
            take()
            out = [a | b for a, b in product(out, one())]
            if len(out) > MAX_CLAUSES:
                raise ValueError(f"over {MAX_CLAUSES} clauses")
        return out

    def one() -> list[frozenset[str]]:
        word = peek()
        if word is None or word == ")" or word.upper() in ("AND", "OR"):
            raise ValueError(f"a word or ( is missing in {expression!r}")
        if take() != "(":
            return [frozenset([word.lower()])]
        out = either()
        if peek() != ")":
            raise ValueError(f") is missing in {expression!r}")
        take()
        return out

    found = either()
    if peek() is not None:
        raise ValueError(f"{peek()!r} is out of place in {expression!r}")
    least = [c for c in set(found) if not any(other < c for other in found)]
    if len(least) > MAX_CLAUSES:
        raise ValueError(f"over {MAX_CLAUSES} clauses")
    return sorted(sorted(c) for c in least)


def parse_simple(text: Column) -> Column:
    """As :func:`to_dnf`, in the engine, for expressions without parentheses."""
    clauses = F.transform(F.split(F.lower(F.trim(text)), r"\s+or\s+"), lambda c: distinct(F.filter(F.split(c, r"\s+and\s+|\s+"), lambda t: t != "")))
    return F.array_sort(F.array_distinct(F.filter(clauses, lambda c: F.size(c) > 0)))
