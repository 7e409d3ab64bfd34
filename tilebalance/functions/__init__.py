"""Functions for use in queries of one's own."""
