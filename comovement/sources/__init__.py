"""Reading and writing points, matches and the prepared store."""
