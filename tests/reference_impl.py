"""Plain sequential versions of the iterative steps, for tests only."""


def components(ids, links):
    near = {i: set() for i in ids}
    for a, b in links:
        near[a].add(b)
        near[b].add(a)
    out = {}
    for i in sorted(ids):
        todo = [i]
        while todo:
            x = todo.pop()
            if x not in out:
                out[x] = i
                todo += near[x]
    return out


def refine(edges, theta):
    """edges: {(a, b): sim} of one cluster -> removed ids in order."""
    active = {x for e in edges for x in e}
    out = []
    while True:
        asim = {}
        for x in active:
            s = [round(v * 1e9) for (a, b), v in edges.items() if x in (a, b) and a in active and b in active]
            if s:
                asim[x] = sum(s) / len(s)
        if not asim:
            return out
        x = min(asim, key=lambda i: (asim[i], -i))
        if asim[x] >= theta * 1e9:
            return out
        active.discard(x)
        out.append(x)


def merge(triplets, sources, size, k):
    """Block-best merging of one block: triplets [(l, sim, r)] -> {old: new}; ties by the original ids."""
    work = [[-s, a, b, a, b] for a, s, b in triplets]
    at = {x: x for t in triplets for x in (t[0], t[2])}
    while work:
        work.sort(key=lambda t: (t[0], t[3], t[4]))
        _, a, b, _, _ = work.pop(0)
        a, b = min(a, b), max(a, b)
        sources[a] |= sources[b]
        size[a] += size[b]
        for x, y in at.items():
            if y == b:
                at[x] = a
        best = {}
        for t in work:
            p, q = sorted((at[t[1]], at[t[2]]))
            if p == q or sources[p] & sources[q] or len(sources[p] | sources[q]) > k or size[p] + size[q] > k:
                continue
            key = (t[0], t[3], t[4])
            if (p, q) not in best or key < (best[p, q][0], best[p, q][3], best[p, q][4]):
                best[p, q] = [t[0], p, q, t[3], t[4]]
        work = list(best.values())
    return at


def star(ids, edges, order):
    near = {i: {} for i in ids}
    for a, b, s in edges:
        near[a][b] = near[b][a] = s
    rank = {i: (len(n) if order == "degree" else sum(round(v * 1e9) for v in n.values()) / max(1, len(n))) for i, n in near.items()}
    covered, out = set(), set()
    for i in sorted(ids, key=lambda x: (-rank[x], x)):
        if i not in covered:
            covered |= {i, *near[i]}
            out |= {(i, i)} | {(i, j) for j in near[i]}
    return out
