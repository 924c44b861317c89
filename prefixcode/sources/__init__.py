"""Run stores, table formats and readers."""
