"""Connected components of very large graphs as plain DataFrame plans."""
