"""A plain set-based miner for small graphs, written from the definitions only."""

from __future__ import annotations

from itertools import product

TYPE, SUB = "rdf:type", "rdfs:subClassOf"


def brute_mine(triples, seeds, k, t, d, l_min, l_max=None, u=False):
    """(neighbour supports, class supports, selected {text: seeds}) of the level-wise procedure."""
    triples = set(triples)
    arcs = {x for x in triples if x[1] not in (TYPE, SUB)}
    inst = {(a, c) for a, p, c in triples if p == TYPE}
    sub = {(a, c) for a, p, c in triples if p == SUB}
    deg = {}
    for a, _, b in arcs:
        for x in {a, b} if u else {a}:
            deg[x] = deg.get(x, 0) + 1
    ok = {}
    for a, p, b in arcs | ({(b, p, a) for a, p, b in arcs} if u else set()):
        if d is None or deg.get(a, 0) <= d:
            ok.setdefault(a, set()).add((p, b))
    dist = {}
    for s in seeds:
        dist[s] = {s: 0}
        front = [s]
        for h in range(1, k + 1):
            front = [b for b in {b for a in front for _, b in ok.get(a, ())} if b not in dist[s]]
            dist[s].update(dict.fromkeys(front, h))
    near = {}
    for s in seeds:
        for v, h in dist[s].items():
            if h:
                near.setdefault(v, set()).add(s)

    def classes(v):
        seen, front = {}, {c for x, c in inst if x == v}
        level = 1
        while front and (t is None or level <= t):
            for c in front:
                seen.setdefault(c, level)
            front = {b for c in front for a, b in sub if a == c} - set(seen)
            level += 1
        return set(seen) | {"TOP"}

    of = {v: classes(v) for v in near}
    tsup = {}
    for v, ss in near.items():
        for c in of[v]:
            tsup.setdefault(c, set()).update(ss)
    freq = {c for c, ss in tsup.items() if len(ss) >= l_min}

    def above(e):
        out, front = set(), {c for x, c in inst if x == e} | {b for a, b in sub if a == e}
        while front:
            out |= front
            front = {b for c in front for a, b in sub if a == c} - out
        return out | {e, "TOP"}

    up = {e: above(e) for e in set(near) | freq}
    paths = {}
    for s in seeds:
        for p, v in ok.get(s, ()):
            if any(dist[x].get(v) == 1 for x in seeds):
                paths.setdefault(((p, v),), set()).add(s)
    patterns_of = {(): set()}
    current = {q: ss for q, ss in paths.items()}
    selected, generated = {}, []
    is_cls = lambda e: e[2]
    for h in range(1, k + 1):
        if h > 1:
            grown = {}
            for q, ss in keep.items():  # noqa: F821
                for p, v in ok.get(q[-1][1], ()):
                    if any(dist[s].get(v) == h for s in ss):
                        grown[(*q, (p, v))] = ss
            current = grown
        if not current:
            break
        caps = {}
        for q, ss in current.items():
            p, v = q[-1]
            head = q[:-1]
            own = tuple((a, b, False) for a, b in head)
            ends = [(p, v, False)] + [(p, c, True) for c in of[v] & freq]
            for pre in [own, *patterns_of.get(head, ())]:
                for e in ends:
                    f = (*pre, e)
                    if any(map(is_cls, f)):
                        caps.setdefault(f, {})[q] = ss
        generated.append(len(current) + len(caps))
        sup = {f: frozenset().union(*m.values()) for f, m in caps.items()}
        live = {f for f, m in caps.items() if len(sup[f]) >= l_min and len(m) > 1}

        def below(a, b):
            return all(x[0] == y[0] and y[1] in up[x[1]] for x, y in zip(a, b, strict=True))

        live = {b for b in live if not any(a != b and sup[a] == sup[b] and below(a, b) and not (below(b, a) and a > b) for a in live)}
        cand = {tuple((p, v, False) for p, v in q): frozenset(ss) for q, ss in current.items()}
        cand |= {f: sup[f] for f in live if not any(frozenset(ss) == sup[f] for ss in caps[f].values())}
        before = dict(selected)
        for f, ss in cand.items():
            if not (l_min <= len(ss) and (l_max is None or len(ss) <= l_max)):
                continue
            clash = [g for g in before if len(g) < len(f) and f[: len(g)] == g and before[g] == ss]
            if not clash:
                selected[f] = ss
            elif not is_cls(f[-1]) and any(is_cls(g[-1]) for g in clash):
                selected[f] = ss
                for g in clash:
                    selected.pop(g, None)
        patterns_of = {}
        for f in live:
            for q in caps[f]:
                patterns_of.setdefault(q, set()).add(f)
        keep = {q: ss for q, ss in current.items() if len(ss) >= l_min or q in patterns_of}
    text = {" ".join(f"-[{p}]-> {e}" for p, e, _ in f): ss for f, ss in selected.items()}
    return near, tsup, text, generated


def count_generalisations(sizes):
    return len(list(product(*(range(n + 1) for n in sizes)))) - 1
