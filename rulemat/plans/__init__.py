"""Control structures on the driver: rule graphs, impact of updates, body order, compilation."""
