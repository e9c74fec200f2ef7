"""The splitter search: state, schedules, counting, rounds, stages and baselines."""
