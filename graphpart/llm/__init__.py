"""Training-data operators. Nothing else in ``graphpart`` imports this subpackage."""
