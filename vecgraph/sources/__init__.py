"""Tables, vector sets derived from them, and the index on disk."""
