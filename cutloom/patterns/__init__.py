"""Pattern graphs: small undirected connected graphs, maybe labelled, as driver-side values."""

from cutloom.patterns.algebra import Pattern, automorphisms, canonical_code, orbits, restriction_sets, restrictions
from cutloom.patterns.catalogue import chain, clique, connected_patterns, cycle, diamond, house, pseudo_cliques, spanning_coefficients, star, tailed_triangle

__all__ = ["Pattern", "automorphisms", "canonical_code", "chain", "clique", "connected_patterns", "cycle", "diamond", "house", "orbits", "pseudo_cliques", "restriction_sets", "restrictions", "spanning_coefficients", "star", "tailed_triangle"]
