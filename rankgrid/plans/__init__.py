"""Cost formulas, schedules, measures and the choice of a plan."""
