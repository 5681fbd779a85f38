"""Questions: three hops over any entities and relations, chains of any length, and their drivers."""

from __future__ import annotations

from dataclasses import dataclass, fields

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ids import eid_value
from ..operators.graph import KnowledgeGraph
from ..operators.hops import CANDIDATES, COMBINE, OUTPUTS, anchor_hop, expand_hop, rerank_hop
from ..operators.topk import check_k


@dataclass(frozen=True)
class ThreeHopQuery:
    """Score a role against anchor 1, re-rank by anchor 2, expand survivors into a target role."""

    anchor1: tuple[str, int]
    relation1: str
    anchor2: tuple[str, int]
    relation2: str
    relation3: str
    k: int = 50
    k2: int | None = None
    role1: str | None = None  # relation whose tails are the role; relation1 where not given
    role3: str | None = None
    role1_end: str = "t"
    role3_end: str = "t"
    candidates1: str = "role"
    candidates3: str = "role"
    combine: str = "replace"
    output: str = "per_head"
    missing: str = "drop"
    bound_share: float = 0.0  # share of role 3 that bounds the scores of the rest before lists are sorted; for large roles

    @classmethod
    def from_spec(cls, spec: dict) -> ThreeHopQuery:
        """A question from plain values, such as parsed JSON."""
        known = {f.name for f in fields(cls)}
        if unknown := set(spec) - known:
            raise ValueError(f"unknown parts of a question: {', '.join(sorted(unknown))}")
        return cls(**{k: tuple(v) if k in ("anchor1", "anchor2") else v for k, v in spec.items()}).validate()

    def validate(self) -> ThreeHopQuery:
        check_k(self.k)
        if self.k2 is not None:
            check_k(self.k2)
        for name, value, known in (
            ("candidates", self.candidates1, CANDIDATES),
            ("candidates", self.candidates3, CANDIDATES),
            ("combine", self.combine, COMBINE),
            ("output", self.output, OUTPUTS),
            ("end", self.role1_end, ("h", "t")),
            ("end", self.role3_end, ("h", "t")),
        ):
            if value not in known:
                raise ValueError(f"unknown {name} {value!r}; known: {', '.join(known)}")
        for etype, key in (self.anchor1, self.anchor2):
            eid_value(etype, key)
        return self

    def relations(self) -> list[str]:
        return list(dict.fromkeys(r for r in (self.relation1, self.relation2, self.relation3, self.role1, self.role3) if r))


@dataclass(frozen=True)
class Hop:
    """A step of a chain: kind 'anchor' (relation, anchor, role), 'rerank' (relation, anchor) or 'expand' (relation, role)."""

    kind: str
    relation: str
    k: int
    anchor: tuple[str, int] | None = None
    role: str | None = None
    role_end: str = "t"
    candidates: str = "role"
    combine: str = "replace"
    output: str = "merged_entities"


def hop_plan(kg: KnowledgeGraph, steps: list[Hop]) -> DataFrame:
    """A chain of hops of any length as one plan; a step in the middle hands its (eid, score) on."""
    if not steps:
        raise ValueError("a chain needs one hop at least")
    state: DataFrame | None = None
    for i, s in enumerate(steps):
        last = i == len(steps) - 1
        if s.kind == "anchor":
            if state is not None:
                raise ValueError("only the first hop of a chain scores a role against an anchor")
            state = anchor_hop(kg, eid_value(*s.anchor), s.relation, kg.role(s.role or s.relation, s.role_end), s.k, s.candidates)
        elif state is None:
            raise ValueError("the first hop of a chain has to score a role against an anchor")
        elif s.kind == "rerank":
            state = rerank_hop(kg, state, eid_value(*s.anchor), s.relation, s.k, s.combine)
        elif s.kind == "expand":
            state = expand_hop(kg, state, s.relation, kg.role(s.role or s.relation, s.role_end), s.k, s.candidates, s.output if last else "merged_entities")
        else:
            raise ValueError(f"unknown hop {s.kind!r}")
    return state


def hop1(kg: KnowledgeGraph, q: ThreeHopQuery, **options) -> DataFrame:
    role = kg.role(q.role1 or q.relation1, q.role1_end)
    return anchor_hop(kg, eid_value(*q.anchor1), q.relation1, role, q.k, q.candidates1, q.missing, **options)


def hop2(kg: KnowledgeGraph, q: ThreeHopQuery, first: DataFrame, keep: bool = False) -> DataFrame:
    return rerank_hop(kg, first, eid_value(*q.anchor2), q.relation2, q.k2 or q.k, q.combine, q.missing, keep)


def hop3(kg: KnowledgeGraph, q: ThreeHopQuery, second: DataFrame, **options) -> DataFrame:
    role = kg.role(q.role3 or q.relation3, q.role3_end)
    return expand_hop(kg, second, q.relation3, role, q.k, q.candidates3, q.output, q.missing, bound_share=q.bound_share, **options)


def three_hop(kg: KnowledgeGraph, q: ThreeHopQuery, **options) -> DataFrame:
    """All three hops as one lazy plan; options choose how hops 1 and 3 keep and merge their lists (form, fan_in, workers).

    Survivors bring their vectors along, so that the table of vectors is read for the two anchors only.
    """
    q.validate()
    return hop3(kg, q, hop2(kg, q, hop1(kg, q, keep=True, **options), keep=True), **options)


#: Rows that one list of the simple algorithm may be asked to hold.
MAX_SHARED_ROWS = 50_000_000


def three_hop_simple(kg: KnowledgeGraph, q: ThreeHopQuery, max_rows: int = MAX_SHARED_ROWS) -> DataFrame:
    """The baseline: vectors are looked up by join, and every list is the shared one - all scores in one row of one reducer, sorted there.

    Refuses roles whose lists no reducer could hold; their sizes are counted only where K times all entities exceeds max_rows.
    """
    from ..operators.hops import anchor_scores, expansion_scores, score_column, shape_output
    from ..operators.hops import composite_of as composite
    from ..operators.lookup import lookup_vectors
    from ..operators.topk import topk_grouped, topk_shared_list

    q.validate()
    if q.combine != "replace" or q.output != "per_head":
        raise ValueError("the baseline knows the plain question only")
    role1, role3 = (kg.role(*x).select("eid") for x in ((q.role1 or q.relation1, q.role1_end), (q.role3 or q.relation3, q.role3_end)))
    if q.k * kg.entity_count() > max_rows and max(role1.count(), q.k * role3.count()) > max_rows:
        raise ValueError(f"the simple algorithm is a baseline for lists of up to {max_rows} rows")
    first = topk_shared_list(anchor_scores(kg, eid_value(*q.anchor1), q.relation1, role1, q.candidates1, q.missing), q.k, None)
    again = lookup_vectors(first.select("eid"), kg.vectors, missing="neg_inf").crossJoin(F.broadcast(composite(kg, eid_value(*q.anchor2), q.relation2))).select("eid", score_column(kg).alias("score"))
    second = topk_shared_list(again, q.k2 or q.k, None)
    scored = expansion_scores(kg, second, q.relation3, role3, q.candidates3, q.missing)
    return shape_output(topk_grouped(scored, q.k, ["head"], "shared_list"), q.k, "per_head")
