"""Matrix operators, solvers and measures."""
