"""Resolvers: Column expressions that give the relation concept of a pair of events.

A relation is symmetric. ``oriented`` hands a pair to its resolver with the smaller type first (by position
inside one type, where resolvers have to be position-free), so a value such as "higher" names a type's side
and does not change with the order of the events.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

Resolver = Callable[[Column, Column], Column]


@dataclass(frozen=True)
class Relation:
    """One taxonomy of a pair of types: a resolver and the tree's text."""

    type_a: str
    type_b: str
    tree: str
    resolve: Resolver

    def __post_init__(self) -> None:
        if self.type_a > self.type_b:
            raise ValueError("name the smaller type first")


def identity(attr: str, tree: str = "Any(=,≠)") -> tuple[str, Resolver]:
    return tree, lambda a, b: F.when(a["attrs"][attr].eqNullSafe(b["attrs"][attr]), F.lit("=")).otherwise(F.lit("≠"))


def compare(attr: str, names: tuple[str, str, str] = ("Higher", "Equal", "Lower")) -> tuple[str, Resolver]:
    """Where the second event's value stands to the first one's."""
    hi, eq, lo = names
    return f"Any({hi},{eq},{lo})", lambda a, b: F.when(b["attrs"][attr] > a["attrs"][attr], hi).when(b["attrs"][attr] < a["attrs"][attr], lo).otherwise(eq)


def lookup(matches: Callable[[Column, Column], Column], outcome: Callable[[Column, Column], Column], hit: str, miss: str, outcomes: list[str]) -> tuple[str, Resolver]:
    """Two levels: ``hit/outcome`` where the pair matches, else ``miss``."""
    tree = f"Any({hi_text(hit, outcomes)},{miss})"
    return tree, lambda a, b: F.when(F.coalesce(matches(a, b), F.lit(False)), F.concat(F.lit(hit + "/"), outcome(a, b))).otherwise(F.lit(miss))


def hi_text(hit: str, outcomes: list[str]) -> str:
    return f"{hit}({','.join(outcomes)})"


def by_expr(tree: str, fn: Resolver) -> tuple[str, Resolver]:
    return tree, fn


def time_lag(bounds: list[int], attr: str = "day") -> tuple[str, Resolver]:
    """Buckets of the distance in time; bucket i ends at ``bounds[i]``."""
    names = [f"within{b}" for b in bounds] + ["beyond"]

    def resolve(a: Column, b: Column) -> Column:
        lag = F.abs(b["attrs"][attr] - a["attrs"][attr])
        out = F.lit("beyond")
        for bound in sorted(bounds, reverse=True):
            out = F.when(lag <= bound, f"within{bound}").otherwise(out)
        return out

    return f"Any({','.join(names)})", resolve


def cosine(attr: str, very: float, some: float) -> tuple[str, Resolver]:
    def dot(x: Column, y: Column) -> Column:
        return F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)

    def resolve(a: Column, b: Column) -> Column:
        x, y = a["attrs"][attr], b["attrs"][attr]
        c = dot(x, y) / F.sqrt(dot(x, x) * dot(y, y))
        return F.when(c >= very, "Similar/Very").when(c >= some, "Similar/Some").otherwise("Dissimilar")

    return "Any(Similar(Very,Some),Dissimilar)", resolve


def contains(attr: str) -> tuple[str, Resolver]:
    """Does one event's text contain the other's?"""
    return "Any(Contains,Apart)", lambda a, b: F.when(F.contains(a["attrs"][attr], b["attrs"][attr]) | F.contains(b["attrs"][attr], a["attrs"][attr]), "Contains").otherwise("Apart")


def oriented(relations: list[Relation]) -> Resolver:
    """(earlier event, later event) -> array of the pair's relation concepts, empty if none is declared."""
    pairs: dict[tuple[str, str], list[Relation]] = {}
    for r in relations:
        pairs.setdefault((r.type_a, r.type_b), []).append(r)

    def resolve(a: Column, b: Column) -> Column:
        out = F.array().cast("array<string>")
        for (x, y), own in pairs.items():
            forward = F.array(*[F.coalesce(r.resolve(a, b), F.lit("")) for r in own])
            if x == y:
                out = F.when((a["type"] == x) & (b["type"] == y), forward).otherwise(out)
            else:
                backward = F.array(*[F.coalesce(r.resolve(b, a), F.lit("")) for r in own])
                out = F.when((a["type"] == x) & (b["type"] == y), forward).when((a["type"] == y) & (b["type"] == x), backward).otherwise(out)
        return out

    return resolve
