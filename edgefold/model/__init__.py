"""The one-sided vertex model: programs, folds, execution strategies and the super-step loop."""
