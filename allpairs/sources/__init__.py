"""Reading and writing: tables, raw rows, joined rows, pairs."""
