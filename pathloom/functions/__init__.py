"""Path expressions, their text forms, automata, and column expressions."""
