"""Programs, pattern recognition, cost formulas, the choice of a strategy and tuning."""
