"""Training-data operators.  Nothing else in ``stablecf`` imports this package."""
