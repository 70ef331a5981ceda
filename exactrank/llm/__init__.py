"""Training-data operators over whole document tables (self-contained subpackage)."""
