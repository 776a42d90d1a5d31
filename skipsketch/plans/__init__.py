"""Query plans over bag algebra, and what can be said about them without running them."""
