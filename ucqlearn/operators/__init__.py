"""The join, union and client operators, and the ledger of what crosses between them."""
