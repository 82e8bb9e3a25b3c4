"""Rule-driven selection of categorical features and interactions on Spark."""
