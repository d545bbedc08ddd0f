"""Named queries with the SQL that recomputes each result from scratch."""
