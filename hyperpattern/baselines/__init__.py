"""Exact baselines: brute force, vertex by vertex, incidence graph, vertex profiles, overlap intersections."""

from ..storage import held
from .bipartite import labelled_arcs
from .bipartite import match as bipartite
from .brute import match as brute
from .overlap import match as overlap
from .profile import index
from .profile import match as profile
from .vertexwise import match as vertexwise

#: What a baseline builds once for a hypergraph, and the argument of its match that takes it.
INDEXES = {"bipartite": ("arc", labelled_arcs), "profile": ("inverted", lambda h: held(index(h), "inverted"))}
BASELINES = {"brute": brute, "vertexwise": vertexwise, "bipartite": bipartite, "profile": profile, "overlap": overlap}
