"""Planning helpers: shared scratch tables, broadcast guards and the product planner."""
