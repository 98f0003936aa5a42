"""Groups of entities whose behaviour is anomalously correlated, found in large event and price streams with Spark."""
