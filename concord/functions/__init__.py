"""Column functions, hardness generators and small exact solvers."""
