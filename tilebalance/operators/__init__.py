"""Keyed Spark operators that apply the heavy/light split to any skewed key."""
