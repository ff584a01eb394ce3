"""Column functions: coins, gaps, edge probabilities, accuracy and cost measures."""
