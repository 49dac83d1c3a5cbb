"""Reading tables, deriving graphs from them, generators, file formats."""
