"""Sort steps and the relational operators on sorted, evenly cut layouts."""
