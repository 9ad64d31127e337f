"""Sources of trips."""
