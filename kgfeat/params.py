"""Parameters of a mining run."""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass, field

from kgfeat.operators.domain import Atom, DomainFilter

TYPE, SUBCLASS, SAME = "rdf:type", "rdfs:subClassOf", "owl:sameAs"
TOP = -1  # the class that every vertex is an instance of
TOP_NAME = "TOP"


@dataclass(frozen=True)
class MiningParams:
    """k: most arcs; t: most class levels (0: the top class alone, None: no bound); d: vertices above
    this degree are not expanded (None: no bound); l_min, l_max: bounds of support, both included;
    u: follow arcs both ways; b_*: blacklists of URIs, or of prefixes if an entry ends in ``*``;
    m: domain filter, 'none' or names of kinds, 'pg' for p or g; atoms: what the kinds are;
    predicate_levels: levels of the predicate hierarchy that patterns may climb (0: none); ids: 'hash' or
    'dense' integers. The other fields switch parts of the method off or choose between forms of it.
    """

    k: int = 3
    t: int | None = 2
    d: int | None = 500
    l_min: int = 5
    l_max: int | None = None
    u: bool = False
    b_predicates: tuple[str, ...] = (TYPE, SUBCLASS)
    b_exp_types: tuple[str, ...] = ()
    b_gen_types: tuple[str, ...] = ()
    m: str | None = None
    atoms: Mapping[str, Atom] = field(default_factory=dict)
    predicate_levels: int = 0
    ids: str = "hash"
    engine: str = "factorised"  # or faithful
    specificity: str = "join"  # trie, hierarchy, off
    prune: bool = True
    drop_single: bool = True
    type_filter: bool = True
    c2: bool = True
    c3: bool = True
    use_top: bool = True
    canonicalise: bool = True
    identity: str = SAME
    seed_hub_exempt: bool = False
    direction_aware: bool = False
    kinds: frozenset[str] = field(default_factory=lambda: frozenset(("neighbour", "path", "pattern")))
    bucket_arcs: int | None = None

    def __post_init__(self) -> None:
        if self.k < 1:
            raise ValueError("k must be 1 or more")
        if self.t is not None and self.t < 0:
            raise ValueError("t must be 0 or more")
        if self.d is not None and self.d < 0:
            raise ValueError("d must be 0 or more")
        if self.l_min < 0 or (self.l_max is not None and self.l_max < self.l_min):
            raise ValueError("0 <= l_min <= l_max must hold")
        if self.engine not in ("factorised", "faithful"):
            raise ValueError(f"unknown engine {self.engine!r}")
        if self.specificity not in ("join", "trie", "hierarchy", "off"):
            raise ValueError(f"unknown specificity {self.specificity!r}")
        if self.ids not in ("hash", "dense"):
            raise ValueError(f"unknown ids {self.ids!r}")
        if self.predicate_levels < 0:
            raise ValueError("predicate_levels must be 0 or more")
        self.domain_filter()  # raises for unknown kinds
        if unknown := self.kinds - {"neighbour", "path", "pattern"}:
            raise ValueError(f"unknown kinds {sorted(unknown)}")

    def domain_filter(self) -> DomainFilter | None:
        return DomainFilter.parse(self.m, self.atoms)
