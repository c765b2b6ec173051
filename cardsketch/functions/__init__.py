"""Hash columns, bias constants, theory and SQL functions."""
