"""Private tree summaries of points on Spark: decompositions, budgets, consistency, range answers."""
