"""Plain functions: expressions, counting, expression classes, and the graph stage of the learners."""
