"""Row-at-a-time kernels with exact counters, for experiments and for work inside one task."""
