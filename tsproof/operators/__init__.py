"""Operators: aggregate trees, proofs, segments, baselines, costs and the relational catalogue."""
