"""Plain reference implementations for the tests."""

from itertools import combinations

S, E = "__START__", "__END__"


def replay(seq, pre, post):
    """(fit, under, over, unbalanced) by the definition: consumption up to an event never above production before it, and equal totals."""
    made = used = 0
    under = False
    for a in seq:
        used += a in post
        under |= used > made
        made += a in pre
    return (not under and made == used, under, made > used, made != used)


def counts(log, pre, post):
    out = [0, 0, 0, 0]
    for seq, f in log:
        for i, x in enumerate(replay(seq, pre, post)):
            out[i] += f * x
    return tuple(out)


def all_places(pre, post, most):
    subs = lambda s: [c for k in range(1, len(s) + 1) for c in combinations(s, k)]
    return [(i, o) for i in subs(pre) for o in subs(post) if len(i) + len(o) <= most]


def random_log(rng, acts="abc", n=8, longest=6):
    log = {}
    for _ in range(n):
        t = (S, *(rng.choice(acts) for _ in range(rng.randint(0, longest))), E)
        log[t] = log.get(t, 0) + rng.randint(1, 5)
    return sorted(log.items())
