"""Training-data operators on the given document tables; nothing else in the package imports this."""
