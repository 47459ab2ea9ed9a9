"""Sample plans, the pass ledger, and tables that cut lineage."""
