"""Boolean relations, and the traversals of automaton and graph together."""
