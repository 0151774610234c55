"""Event sources, generators and the written ledger."""
