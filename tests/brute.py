"""Plain Python references: mining, selection, overlap by automata, order-only counting."""

from itertools import combinations, permutations, product


def starts(events, types, gaps):
    have, out = set(events), []
    for e, t in sorted(events, key=lambda x: x[1]):
        if e == types[0]:
            at, ok = t, True
            for x, g in zip(types[1:], gaps, strict=True):
                at += g
                ok &= (x, at) in have
            if ok:
                out.append(t)
    return out


def frequent(events, tg, least, longest=4):
    """{(types, gaps): starts} of all injective multi-node episodes at or above the threshold."""
    types = sorted({e for e, _ in events})
    out = {}
    for n in range(2, longest + 1):
        for some in permutations(types, n):
            for gaps in product(range(1, tg + 1), repeat=n - 1):
                s = starts(events, some, gaps)
                if len(s) >= least:
                    out[some, gaps] = s
    return out


def covered(types, gaps, begin):
    out, at = set(), 0
    for e, g in zip(types, (0, *gaps), strict=True):
        at += g
        out |= {(e, s + at) for s in begin}
    return out


def overlap_by_automata(events, episodes):
    """One pass over events in time; automata wait for their next type. {(a, b): events both cover}."""
    begins = {k: set(starts(events, *k)) for k in episodes}
    waiting, shared = {}, {}
    for e, t in sorted(events, key=lambda x: (x[1], x[0])):
        took = [k for k in episodes if k[0][0] == e and t in begins[k]]
        for k in took:
            waiting.setdefault(k[0][1], []).append((k, 1, t, t + k[1][0]))
        keep = []
        for k, i, s, due in waiting.pop(e, []):
            if due != t:
                keep.append((k, i, s, due))
                continue
            took.append(k)
            if i + 1 < len(k[0]):
                waiting.setdefault(k[0][i + 1], []).append((k, i + 1, s, t + k[1][i]))
        if keep:
            waiting.setdefault(e, []).extend(x for x in keep if x[3] > t)
        for a, b in combinations(sorted(set(took)), 2):
            shared[a, b] = shared.get((a, b), 0) + 1
    return shared


def total(events, chosen):
    """Units of a set of multi-node episodes {(types, gaps): starts}; single events cover the rest."""
    rest = set(events) - set().union(*(covered(*k, s) for k, s in chosen.items())) if chosen else set(events)
    return sum(2 * len(k[0]) + len(s) + 1 for k, s in chosen.items()) + len(rest) + 3 * len({e for e, _ in rest})


def best_subset(events, cands):
    return min(total(events, dict(some)) for n in range(len(cands) + 1) for some in combinations(cands.items(), n))


def fifo(line, types):
    """Event-disjoint serial occurrences by first-come queues; line: (t, e), equal times don't follow one another."""
    queue = [[] for _ in types]
    done = 0
    for t, e in sorted(line):
        if e not in types:
            continue
        i = types.index(e)
        if i == 0:
            queue[0].append(t)
        else:
            ready = [x for x in queue[i - 1] if x < t]
            if not ready:
                continue
            queue[i - 1].remove(min(ready))
            queue[i].append(t)
        if i == len(types) - 1:
            done += 1
    return done
