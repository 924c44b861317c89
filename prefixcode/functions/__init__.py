"""Code arithmetic, key normalisation, measures and user-defined functions."""
