"""Grids, anchor specifications and box plans: metadata only, all on the driver."""
