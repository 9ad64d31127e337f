"""Dense flow blocks over origin, destination and time, on Spark."""
