"""All valid walks of small graphs, enumerated in plain Python."""

import random

RULES = {
    "succeeds": lambda a, b: a[3] <= b[2],
    "strictly_succeeds": lambda a, b: a[3] < b[2],
    "overlaps": lambda a, b: a[2] < b[2] and a[3] < b[3],
    "overlaps_proper": lambda a, b: a[2] < b[2] < a[3] < b[3],
}


def random_edges(seed, zero=True):
    r = random.Random(seed)
    n, m = r.randint(2, 7), r.randint(1, 12)
    out = []
    for _ in range(m):
        s = r.randint(0, 8)
        out.append((r.randrange(n), r.randrange(n), s, s + r.randint(0 if zero else 1, 3), float(r.randint(0, 5))))
    return out


def walks(edges, source, ta, tb, kind):
    inside = [k for k, e in enumerate(edges) if e[2] >= ta and e[3] <= tb]
    rule, stack = RULES[kind], [[k] for k in inside if edges[k][0] == source]
    while stack:
        w = stack.pop()
        yield [edges[k] for k in w]
        last = edges[w[-1]]
        stack += [[*w, k] for k in inside if k not in w and edges[k][0] == last[1] and rule(last, edges[k])]


def answers(edges, source, ta, tb, kind):
    """Best values for every vertex but the source: arrival, duration, cost, weight, hops."""
    best = {}
    for w in walks(edges, source, ta, tb, kind):
        v = w[-1][1]
        row = (w[-1][3], w[-1][3] - w[0][2], sum(e[3] - e[2] for e in w), sum(e[4] for e in w), len(w))
        best[v] = tuple(map(min, best.get(v, row), row))
    best.pop(source, None)
    return best


def departures(edges, target, ta, tb, kind):
    best = {}
    for s in {e[0] for e in edges} - {target}:
        for w in walks(edges, s, ta, tb, kind):
            if w[-1][1] == target:
                best[s] = max(best.get(s, w[0][2]), w[0][2])
    return best


def betweenness(edges, ta, tb, kind):
    """Scores over least-duration walks, edge sequences counted."""
    score = {v: 0.0 for e in edges if e[2] >= ta and e[3] <= tb for v in e[:2]}
    for s in list(score):
        by = {}
        for w in walks(edges, s, ta, tb, kind):
            if w[-1][1] != s:
                by.setdefault(w[-1][1], []).append((sum(e[3] - e[2] for e in w), w))
        for found in by.values():
            least = min(c for c, _ in found)
            tied = [w for c, w in found if c == least]
            for w in tied:
                for e in w[:-1]:
                    score[e[1]] += 1 / len(tied)
    return score
