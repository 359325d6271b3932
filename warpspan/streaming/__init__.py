"""The methods over unbounded input."""
