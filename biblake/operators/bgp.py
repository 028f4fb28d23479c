"""Graph patterns over triples: joins, alternatives, options, and what is asked of their bindings."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Pattern = tuple[str, str, str]


def _var(x: str) -> bool:
    return x.startswith("?")


def _match(triples: DataFrame, pattern: Pattern) -> DataFrame:
    """The bindings of one pattern; a constant predicate prunes, a variable that repeats must agree."""
    out = triples
    names: dict[str, str] = {}
    for place, x in zip("spo", pattern):
        if not _var(x):
            out = out.where(F.col(place) == x)
        elif x in names:
            out = out.where(F.col(place) == F.col(names[x]))
        else:
            names[x] = place
    return out.select(*[F.col(c).alias(v[1:]) for v, c in names.items()])


def order(patterns: list[Pattern], sizes: dict[str, int] | None = None) -> list[Pattern]:
    """Patterns so that each shares a variable with an earlier one, the most selective first; an error if they fall apart."""
    sizes = sizes or {}
    cost = lambda p: (sum(map(_var, p)), sizes.get(p[1], 1 << 60), p)
    todo, out, bound = sorted(patterns, key=cost), [], set()
    while todo:
        pick = next((p for p in todo if not out or bound & {x for x in p if _var(x)}), None)
        if pick is None:
            raise ValueError("the patterns share no variable: that would be a product")
        todo.remove(pick)
        out.append(pick)
        bound |= {x for x in pick if _var(x)}
    return out


def bgp(triples: DataFrame, patterns: list[Pattern], where: Column | None = None, optional: list[Pattern] = (), sizes: dict[str, int] | None = None) -> DataFrame:
    """One column a variable (without its question mark); ``optional`` patterns are left-joined; ``where`` filters the result."""
    found = None
    for p in order(patterns, sizes):
        part = _match(triples, p)
        found = part if found is None else found.join(part, [c for c in part.columns if c in found.columns])
    for p in optional:
        part = _match(triples, p)
        found = found.join(part, [c for c in part.columns if c in found.columns], "left")
    return found if where is None else found.where(where)


@dataclass(frozen=True)
class Question:
    """What is asked of the bindings of some patterns.

    branches: alternatives, each a list of patterns that must all hold; a variable that a branch lacks is null in its bindings.
    show: variables (without question mark) to give back, all by default. by: variables to group by, ``n`` being the number of bindings, or with
    ``count`` the number of different values of that variable. order: (column, descending) pairs; limit: rows of a report, after order.
    """

    branches: tuple[tuple[Pattern, ...], ...]
    optional: tuple[Pattern, ...] = ()
    where: Column | None = None
    show: tuple[str, ...] = ()
    distinct: bool = False
    by: tuple[str, ...] | None = None
    count: str | None = None
    order: tuple[tuple[str, bool], ...] = ()
    limit: int | None = None
    sizes: dict[str, int] = field(default_factory=dict)


def answer(triples: DataFrame, question: Question) -> DataFrame:
    """The bindings or counts that are asked for. Only the predicates that the patterns name are read, if all of them are constants."""
    q = question
    named = {p[1] for b in (*q.branches, q.optional) for p in b}
    if not any(map(_var, named)):
        triples = triples.where(F.col("p").isin(*sorted(named)))
    parts = [bgp(triples, list(b), optional=list(q.optional), sizes=q.sizes) for b in q.branches]
    found = reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), parts)
    if q.where is not None:
        found = found.where(q.where)
    if q.by is not None:
        if q.distinct:
            found = found.select(*dict.fromkeys((*q.by, *q.show, *([q.count] if q.count else [])))).distinct()
        found = found.groupBy(*q.by).agg((F.count_distinct(q.count) if q.count else F.count("*")).alias("n"))
    elif q.show or q.distinct:
        found = found.select(*q.show) if q.show else found
        found = found.distinct() if q.distinct else found
    if q.order:
        found = found.orderBy(*[F.desc(c) if down else F.asc(c) for c, down in q.order])
    return found if q.limit is None else found.limit(q.limit)
