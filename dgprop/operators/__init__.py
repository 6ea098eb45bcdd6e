"""Graph algebra, filters, propagation, incremental repair, sequences, tasks and metrics."""
