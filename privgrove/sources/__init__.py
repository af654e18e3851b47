"""Reading and writing tables, models and ledgers."""
