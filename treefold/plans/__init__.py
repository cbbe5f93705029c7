"""Driver loops: iteration, hashing, decomposition and merge schedules."""
