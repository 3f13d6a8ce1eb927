"""The worked example's graph and what it must give."""

TRIPLES = [
    ("n1", "p4", "v1"), ("n2", "p4", "v1"), *[("v1", "p7", f"w{i}") for i in range(1, 6)],
    ("n1", "p1", "v2"), ("n2", "p1", "v4"), ("v2", "p2", "v3"), ("v4", "p2", "v5"), ("v3", "p3", "v6"), ("v5", "p3", "v6"),
    ("n1", "p6", "v8"), ("n2", "p6", "v9"), ("v7", "p5", "n2"),
    ("v2", "rdf:type", "T1"), ("v4", "rdf:type", "T1"), ("v3", "rdf:type", "T2"), ("T2", "rdfs:subClassOf", "T3"), ("v5", "rdf:type", "T4"), ("T4", "rdfs:subClassOf", "T3"),
    *[(v, "rdf:type", t) for v in ("v8", "v9") for t in ("T5", "T6")],
]
SEEDS = ["n1", "n2"]
BASE = dict(k=3, t=2, d=4, l_min=2, l_max=3)
GOLD = {"-[p4]-> v1", "-[p6]-> T5", "-[p6]-> T6", "-[p1]-> T1 -[p2]-> T3 -[p3]-> v6"}
