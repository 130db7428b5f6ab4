"""Recovery operators: ledger, live view, search, contiguous passes, work pool, reassembly, scoring."""
