"""Plan pieces: running sums, overlap joins, deterministic operators, worlds, baselines."""
