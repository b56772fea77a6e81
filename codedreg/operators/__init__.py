"""Methods, measures and their relational surroundings."""
