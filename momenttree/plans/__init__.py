"""Construction of trees: which scans run, in which engine, for which nodes."""
