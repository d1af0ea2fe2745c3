"""Graph preliminaries, traversals, the label index and its maintainers."""
