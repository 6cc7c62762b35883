"""Driver-side planning: patterns to conjunctive queries, shapes, bounds, orders, strategies."""
