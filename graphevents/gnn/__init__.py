"""Graph layers in two physical forms: relational (DataFrames) and kernel (numpy on sentence groups)."""
