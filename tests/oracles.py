"""Independent brute-force versions, in plain Python over small lists."""

from itertools import permutations

OPEN = 1 << 62


def fold(rows, strict=True):
    """Versions and codes of (batch, op, vt_s, vt_e, w, tt) rows of one identity, written one after the other."""
    live, closed, codes = [], [], []
    for batch, op, start, end, w, tt in rows:
        end = OPEN if op == "retract" else end
        hit = [p for p in live if p[0] < end and p[1] > start]
        code = None
        if op != "retract" and start >= end:
            code = "F_EMPTY_INTERVAL"
        elif op == "retract" and not hit:
            code = "F_NOTHING_TO_RETRACT"
        elif op == "correct" and strict and not hit:
            code = "F_NOTHING_TO_CORRECT"
        codes.append((batch, code))
        if code:
            continue
        live = [p for p in live if p not in hit]
        for p in hit:
            closed.append((p[0], p[1], p[2], tt, p[3]))
            if p[0] < start:
                live.append((p[0], min(p[1], start), tt, p[3]))
            if p[1] > end:
                live.append((max(p[0], end), p[1], tt, p[3]))
        if op != "retract":
            live.append((start, end, tt, w))
    return sorted(closed + [(p[0], p[1], p[2], OPEN, p[3]) for p in live]), codes


def reach(edges, source, t_from, t_to, max_wait=None, strict=True, max_hops=None):
    """{node: arrival} by search over all (node, arrival, hops) labels."""
    labels, todo = {(source, t_from, 0)}, [(source, t_from, 0)]
    while todo:
        node, at, hops = todo.pop()
        if max_hops is not None and hops >= max_hops:
            continue
        for _, a, b, t in edges:
            if a != node or a == b or not t_from <= t <= t_to or (t <= at if strict else t < at):
                continue
            if max_wait is not None and hops > 0 and t - at > max_wait:
                continue
            label = (b, t, hops + 1 if max_hops is not None else 1)
            if label not in labels:
                labels.add(label)
                todo.append(label)
    out = {}
    for node, at, _ in labels:
        out[node] = min(at, out.get(node, at))
    return out


def motif_count(edges, pattern, delta):
    """Instances of a pattern by trying every ordered choice of edges."""
    live = sorted((t, eid, a, b) for eid, a, b, t in edges if a != b)
    n = 0
    for chosen in permutations(live, len(pattern)):
        if any(x[:2] >= y[:2] for x, y in zip(chosen, chosen[1:])) or chosen[-1][0] - chosen[0][0] > delta:
            continue
        names, fine = {}, True
        for (p, q), (_, _, a, b) in zip(pattern, chosen):
            for role, node in ((p, a), (q, b)):
                if names.setdefault(role, node) != node:
                    fine = False
        n += fine and len(set(names.values())) == len(names)
    return n


def paths(edges, src, dst, t_from, t_to, k, max_hops):
    out, todo = [], [([src], [], t_from)]
    while todo:
        nodes, eids, at = todo.pop()
        if nodes[-1] == dst and eids:
            out.append((at, len(eids), eids, nodes))
            continue
        if len(eids) == max_hops:
            continue
        todo += [([*nodes, b], [*eids, eid], t) for eid, a, b, t in edges if a == nodes[-1] and b not in nodes and t_from < t <= t_to and t > at]
    return sorted(out)[:k]


def khop(edges, seeds, k):
    found, front = {s: 0 for s in seeds}, set(seeds)
    for hop in range(1, k + 1):
        front = {b for _, a, b, _ in edges if a in front} - set(found)
        found |= {n: hop for n in front}
    return found


def relation(a, b):
    (s, e), (x, y) = a, b
    tests = {
        "before": e < x, "meets": e == x, "overlaps": s < x < e < y, "starts": s == x and e < y, "during": x < s and e < y, "finishes": e == y and s > x, "equals": (s, e) == (x, y),
        "finished_by": e == y and s < x, "contains": s < x and y < e, "started_by": s == x and e > y, "overlapped_by": x < s < y < e, "met_by": y == s, "after": y < s,
    }
    held = [r for r, ok in tests.items() if ok]
    assert len(held) == 1, (a, b, held)
    return held[0]
