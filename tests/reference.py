"""Plain loops over dictionaries, to hold the engine against."""


def out_neighbours(edges):
    out = {}
    for a, b in edges:
        out.setdefault(a, set()).add(b)
    return out


def vertices(edges):
    return {x for e in edges for x in e}


def rank(edges, verts=None, beta=0.85, rounds=30, start=None, init=1.0):
    verts = vertices(edges) if verts is None else set(verts)
    out, score = out_neighbours(edges), {v: (start or {}).get(v, init) for v in verts}
    for _ in range(rounds):
        got = dict.fromkeys(verts, 0.0)
        for a, targets in out.items():
            for b in targets:
                got[b] += score[a] / len(targets)
        score = {v: 1 - beta + beta * got[v] for v in verts}
    return score


def approximate(edges, hot, previous, verts, beta=0.85, rounds=30):
    out = out_neighbours(edges)
    score = {v: previous.get(v, 1.0) for v in hot}
    inflow = dict.fromkeys(hot, 0.0)
    for a, targets in out.items():
        for b in targets:
            if a not in hot and b in hot:
                inflow[b] += previous[a] / len(targets)
    for _ in range(rounds):
        got = dict.fromkeys(hot, 0.0)
        for a in hot & set(out):
            for b in out[a] & hot:
                got[b] += score[a] / len(out[a])
        score = {v: 1 - beta + beta * (got[v] + inflow[v]) for v in hot}
    return {v: score.get(v, previous.get(v, 1 - beta)) for v in verts}


def hops(edges, seeds, n):
    out, seen, front = out_neighbours(edges), dict.fromkeys(seeds, 0), set(seeds)
    for h in range(1, n + 1):
        front = {b for a in front for b in out.get(a, ())} - set(seen)
        seen |= dict.fromkeys(front, h)
    return {v: h for v, h in seen.items() if h}


def overlap(a, b, k, p):
    total = 0.0
    for d in range(1, k + 1):
        total += p ** (d - 1) * len(set(a[:d]) & set(b[:d])) / d
    return (1 - p) * total


def extrapolated_uneven(short, long, p):
    s, l = len(short), len(long)  # noqa: E741
    x = lambda d: len(set(short[:d]) & set(long[:d]))
    total = sum(x(d) / d * p**d for d in range(1, l + 1)) + sum(x(s) * (d - s) / (s * d) * p**d for d in range(s + 1, l + 1))
    return (1 - p) / p * total + ((x(l) - x(s)) / l + x(s) / s) * p**l
