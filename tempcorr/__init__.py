"""When, at which time scale, how strongly and in which direction pairs of time series depend on each other."""
