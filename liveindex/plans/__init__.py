"""The stored index and the plans over it."""
