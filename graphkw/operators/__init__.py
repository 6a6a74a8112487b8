"""The parts of a search: waves, bounds, demands, partitions, sketches."""
