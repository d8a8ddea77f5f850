"""Placing sites along paths, on Spark: distances, detours, covering sets, greedy and indexed placement."""
