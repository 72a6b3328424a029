"""DataFrame operators for the construction pipeline and the evaluation layer."""
