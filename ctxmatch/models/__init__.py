"""Column-to-table models: the perceptron, its training as a set of Spark tasks, and prediction."""
