"""pathflow: problem solving by graph traversal, as Catalyst plans."""
