"""Box sums and averages over large grids, answered from tile-level cumulative sums."""
