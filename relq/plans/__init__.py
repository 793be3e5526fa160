"""What holds plans together: shared tables and the registry of queries."""
