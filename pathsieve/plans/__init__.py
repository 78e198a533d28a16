"""Label automata, pruning aggregates and query specifications: driver-side planning, no row is touched here."""
