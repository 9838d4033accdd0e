"""Cost rules, measures and plan checks."""
