"""Building anchor tables and answering boxes from them, and the baselines."""
