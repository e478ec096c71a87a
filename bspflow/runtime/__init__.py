"""Running a program: the superstep loop, global state, checkpoints, statistics, failures, job pipelines."""
