"""Tables, edge tables derived from them, triple files, and written intermediate tables."""
