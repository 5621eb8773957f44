"""Classes of path expressions and what follows from them."""

from __future__ import annotations

from dataclasses import dataclass

from pathq.plans.automaton import to_nfa
from pathq.plans.expr import Concat, Empty, Expr, Star, Symbol, Union, as_expr

Word = tuple[Symbol, ...]


@dataclass(frozen=True)
class QueryClass:
    star_free: bool
    nullable: bool
    closure_label: Symbol | None  # of x* and x+
    reflexive: bool  # x* rather than x+
    canonical: tuple[Symbol, Symbol, Symbol] | None  # of a b* c
    word: Word | None  # of a plain concatenation
    labels: frozenset[str] | None  # None: any label may matter
    finite: bool

    @property
    def name(self) -> str:
        if self.closure_label is not None:
            return "closure"
        if self.star_free:
            return "word" if self.word is not None else "star-free"
        return "canonical" if self.canonical else "general"


def is_star_free(x: Expr) -> bool:
    if isinstance(x, Star):
        return False
    return all(map(is_star_free, x.parts)) if isinstance(x, Concat | Union) else True


def used_labels(expr: Expr | str) -> frozenset[str] | None:
    """Labels that can occur on an answer path; None if a wildcard lets any occur."""
    x = as_expr(expr)
    if isinstance(x, Symbol):
        return None if x.but is not None else frozenset({x.label})
    parts = x.parts if isinstance(x, Concat | Union) else (x.body,) if isinstance(x, Star) else ()
    told = [used_labels(p) for p in parts]
    return None if None in told else frozenset().union(*told)


def classify(expr: Expr | str) -> QueryClass:
    x = as_expr(expr)
    plain = lambda y: isinstance(y, Symbol)
    closure, reflexive, canonical, word = None, False, None, None
    if isinstance(x, Star) and plain(x.body):
        closure, reflexive = x.body, True
    elif isinstance(x, Concat) and len(x.parts) == 2 and plain(x.parts[0]) and x.parts[1] == Star(x.parts[0]):
        closure = x.parts[0]
    elif isinstance(x, Concat) and len(x.parts) == 3 and plain(x.parts[0]) and isinstance(x.parts[1], Star) and plain(x.parts[1].body) and plain(x.parts[2]):
        canonical = (x.parts[0], x.parts[1].body, x.parts[2])
    if plain(x):
        word = (x,)
    elif isinstance(x, Empty):
        word = ()
    elif isinstance(x, Concat) and all(map(plain, x.parts)):
        word = x.parts
    free = is_star_free(x)
    return QueryClass(free, to_nfa(x).nullable, closure, reflexive, canonical, word, used_labels(x), free)


def expand_words(expr: Expr | str, limit: int = 256) -> tuple[list[Word], bool]:
    """(words but the empty one, whether the empty one belongs) of a star-free expression: unions moved outside concatenations.

    Raises ``OverflowError`` above ``limit`` words; the layered evaluation has no such limit.
    """

    def words(x: Expr) -> list[Word]:
        if isinstance(x, Empty):
            return [()]
        if isinstance(x, Symbol):
            return [(x,)]
        if isinstance(x, Union):
            out = list(dict.fromkeys(w for p in x.parts for w in words(p)))
        elif isinstance(x, Concat):
            out = [()]
            for p in x.parts:
                out = list(dict.fromkeys(a + b for a in out for b in words(p)))
                if len(out) > limit:
                    break
        else:
            raise ValueError("the expression has a star")
        if len(out) > limit:
            raise OverflowError(f"more than {limit} words")
        return out

    found = words(as_expr(expr))
    return [w for w in found if w], () in found
