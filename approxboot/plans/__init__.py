"""Planning of sample size and resample count, the early-answer loop, baselines and costs."""
