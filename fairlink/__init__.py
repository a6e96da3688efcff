"""Private record linkage on Spark under privacy, fairness and cost constraints."""
