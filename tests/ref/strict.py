"""Plain-Python determination in strict order of size, point by point."""

from unscramble.operators.runs import runs_union_find


def smooth_two_pass(runs, last, theta, len2, mode, hard):
    """runs: 1-runs (l, r); hard: positions that must stay 0."""
    out = []
    original = {}
    for l, r in runs:
        if out:
            pl, pr = original[len(original) - 1]
            gap = l - pr - 1
            if gap < theta * ((r - l + 1) + (pr - pl + 1)) and not any(p in hard for p in range(pr + 1, l)):
                out[-1] = (out[-1][0], r)
                original[len(original)] = (l, r)
                continue
        out.append((l, r))
        original[len(original)] = (l, r)
    keep = []
    for i, (l, r) in enumerate(out):
        before = l - (out[i - 1][1] if i else 0) - 1
        after = (out[i + 1][0] if i + 1 < len(out) else last + 1) - r - 1
        short = before > 0 and after > 0 and (r - l + 1) < theta * (before + after)
        if mode == "guarded":
            short = short and (r - l + 1) < len2
        if not short:
            keep.append((l, r))
    return keep


def strict_order(points, last, len1, len2, theta, mode="guarded"):
    """points: {cycle tuple: set of n}. Returns {cycle: [(l, r)]}."""
    key = lambda c: ">".join(map(str, c))
    order = sorted((c for c in points if len(points[c]) >= len1), key=lambda c: (-len(points[c]), key(c)))
    claimed = {}
    out = {}
    for c in order:
        taken = set().union(*[claimed.get(s, set()) for s in c])
        bits = [1 if n in points[c] and n not in taken else 0 for n in range(1, last + 1)]
        runs = [(l, r) for b, l, r in runs_union_find(bits) if b]
        kept = [(l, r) for l, r in smooth_two_pass(runs, last, theta, len2, mode, taken) if r - l + 1 >= len2]
        out[c] = kept
        for s in c:
            claimed.setdefault(s, set()).update(n for l, r in kept for n in range(l, r + 1))
    return {c: v for c, v in out.items() if v}
