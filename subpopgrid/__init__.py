"""Many statistics over many subpopulations, from one bounded, mergeable state."""
