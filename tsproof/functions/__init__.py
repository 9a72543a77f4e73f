"""Column and plain-Python functions shared by server and client: commitments, covers, line models."""
