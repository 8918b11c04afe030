"""Growing trees: parameters, schedules, protocol, models and baselines."""
