"""DataFrame operators that produce or use prefix codes."""
