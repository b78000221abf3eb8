"""Reading tables and files, and writing matrices."""
