"""Graph-pattern plans: weaving, text, evaluation."""
