"""A sort-centred analytics engine: sorted DataFrames carry prefix codes."""
