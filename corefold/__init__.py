"""corefold: dense multi-way arrays from tables, compressed as a small core and one factor per mode."""
