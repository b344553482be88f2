"""Covariate choice from a causal graph of a few dozen nodes (on the driver; its result prunes columns)."""

from __future__ import annotations

from itertools import combinations


def _children(dag):
    nodes = set(dag) | {c for cs in dag.values() for c in cs}
    return {n: set(dag.get(n, ())) for n in nodes}


def _reach(step, start):
    seen, todo = set(start), list(start)
    while todo:
        for n in step.get(todo.pop(), ()):
            if n not in seen:
                seen.add(n)
                todo.append(n)
    return seen


def descendants(dag, node):
    return _reach(_children(dag), [node]) - {node}


def _parents(dag):
    out = {n: set() for n in _children(dag)}
    for n, cs in _children(dag).items():
        for c in cs:
            out[c].add(n)
    return out


def d_separated(dag, xs, ys, given) -> bool:
    """Whether ``given`` blocks every path between ``xs`` and ``ys``: they are apart in the
    moral graph of the ancestors of all of them."""
    parents = _parents(dag)
    keep = _reach(parents, [*xs, *ys, *given])
    links = {n: set() for n in keep}
    for n in keep:
        up = parents[n] & keep
        for p in up:
            links[n].add(p)
            links[p].add(n)
        for a, b in combinations(sorted(up), 2):
            links[a].add(b)
            links[b].add(a)
    open_links = {n: m - set(given) for n, m in links.items() if n not in given}
    return not _reach(open_links, [x for x in xs if x not in given]) & set(ys)


def minimal_adjustment_set(dag, treatment, outcome, observed):
    """A smallest set of observed non-descendants of the treatment that blocks all back-door
    paths; None if there is none. Ties go to the alphabetically first set."""
    back = {n: cs - ({*cs} if n == treatment else set()) for n, cs in _children(dag).items()}
    usable = sorted(set(observed) - {treatment, outcome} - descendants(dag, treatment))
    for size in range(len(usable) + 1):
        for chosen in combinations(usable, size):
            if d_separated(back, [treatment], [outcome], set(chosen)):
                return set(chosen)
    return None


def check_pretreatment(dag, treatment, covariates) -> None:
    """Raise if a covariate is affected by the treatment."""
    bad = sorted(set(covariates) & descendants(dag, treatment))
    if bad:
        raise ValueError(f"affected by {treatment}: {', '.join(bad)}")
