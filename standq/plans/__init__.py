"""Relations, proofs, incremental derivation and the statement front end."""
