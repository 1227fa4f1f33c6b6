"""Language models, prices and the ledger of their calls."""
