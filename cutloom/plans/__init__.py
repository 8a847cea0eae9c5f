"""Planning: cuts, collisions, cost models, an intermediate representation and the search."""
