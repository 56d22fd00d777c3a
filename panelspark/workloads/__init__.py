"""The queries of the catalogue, by subject; each has its SQL beside it where SQL can say it."""
