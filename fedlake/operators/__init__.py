"""DataFrame operators: packing, sampling, sequences, privacy, ranking, relational helpers."""
