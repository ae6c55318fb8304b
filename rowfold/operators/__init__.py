"""Statistical, machine-learning and text methods."""
