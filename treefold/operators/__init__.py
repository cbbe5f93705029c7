"""DataFrame operators: binary extension, piece engines, merges, baselines, relational helpers."""
