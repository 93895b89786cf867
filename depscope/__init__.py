"""depscope: rule-based schema analysis and functional-dependency propagation on Spark."""
