"""kgflow: incremental knowledge-graph construction as DataFrame plans."""
