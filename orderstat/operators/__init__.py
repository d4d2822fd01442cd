"""Selection: distribution over pivots, exact counts, pruning, and the engine that repeats them."""
