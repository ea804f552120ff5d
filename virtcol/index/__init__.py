"""What stands in for an index where only a budget of rows may be judged: features, strata, samples, estimators, search."""
