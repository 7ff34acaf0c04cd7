"""Plans as data: filter orders for each document, join plans, their costs."""
