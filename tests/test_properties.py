"""Small random hypergraphs against the definition: injective, label-preserving vertex mappings."""

import random
from itertools import permutations

import pytest

from hyperpattern.baselines import BASELINES
from hyperpattern.candidates import build_space, prune_to_fixpoint, prune_worklist
from hyperpattern.model import HypergraphFrame
from hyperpattern.pattern import PatternGraph
from hyperpattern.search import match


def by_definition(p, data, label):
    """Edge assignments that some vertex mapping makes."""
    sets = {frozenset(vs): e for e, vs in data.items()}
    us = [u for u, _ in p.labels]
    out = set()
    for image in permutations(label, len(us)):
        if all(label[v] == p.label[u] for u, v in zip(us, image, strict=True)):
            phi = dict(zip(us, image, strict=True))
            found = [sets.get(frozenset(phi[u] for u in e)) for e in p.edges]
            if None not in found:
                out.add(tuple(found))
    return sorted(out)


def one(seed):
    r = random.Random(seed)
    n = r.randint(5, 6)
    label = {v: r.choice("AB") for v in range(n)}
    data = {}
    for e in range(r.randint(5, 8)):
        vs = tuple(sorted(r.sample(range(n), r.randint(1, 3))))
        if vs not in data.values():
            data[e] = vs
    edges = r.sample(sorted(data), min(r.randint(1, 3), len(data)))
    return PatternGraph.of([data[e] for e in edges], label), data, label, tuple(edges)


@pytest.mark.parametrize("seed", range(5))
def test_engines_against_the_definition(spark, seed):
    p, data, label, identity = one(seed)
    h = HypergraphFrame.from_incidence(spark.createDataFrame([(e, v, label[v]) for e, vs in data.items() for v in vs], "e long, v long, label string")).materialise()
    want = by_definition(p, data, label)
    got = lambda df: sorted(tuple(x) for x in df.collect())
    assert identity in want
    assert got(match(h, p, engine="local")) == want
    assert got(match(h, p, engine="wavefront")) == want
    for name in ("brute", "vertexwise", "profile", "overlap", "bipartite"):
        assert got(BASELINES[name](h, p)) == want, name
    space = build_space(p, h)
    ids = lambda s: got(s.candidates.select("q", "f"))
    kept = prune_to_fixpoint(p, space)
    assert ids(kept) == ids(prune_worklist(p, space)) == ids(prune_to_fixpoint(p, kept))
    assert {(q, m[q]) for m in want for q in range(p.size)} <= set(ids(kept))


def test_labels_removed_only_add(spark):
    p, data, label, _ = one(3)
    frame = lambda l: HypergraphFrame.from_incidence(spark.createDataFrame([(e, v, l[v]) for e, vs in data.items() for v in vs], "e long, v long, label string"))
    plain = {v: "" for v in label}
    with_labels = {tuple(x) for x in match(frame(label), p).collect()}
    without = {tuple(x) for x in match(frame(plain), PatternGraph.of(p.edges, {u: "" for u, _ in p.labels})).collect()}
    assert with_labels <= without


def test_wide_patterns():
    chain = PatternGraph.of([[i, i + 1] for i in range(62)], {i: "" for i in range(63)})
    assert chain.full.bit_count() == 62 and chain.adjacent[30].bit_count() == 2
    with pytest.raises(ValueError):
        PatternGraph.of([[i, i + 1] for i in range(64)], {i: "" for i in range(65)})
