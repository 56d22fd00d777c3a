"""The methods."""
