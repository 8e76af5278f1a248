"""What is decided before data moves: fan-out, learned distribution functions, cuts."""
