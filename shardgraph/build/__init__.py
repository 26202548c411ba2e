"""From tables to prepared graphs."""
