"""Continuous form: counts of tiles by window, and maps renewed batch by batch."""
