"""Loop programs, their transformations, policies and the sweep runtime."""
