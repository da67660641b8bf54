"""Reading tables and files, and writing results."""
