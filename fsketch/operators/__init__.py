"""The method's steps, its solvers, baselines and measures."""
