"""rowfold: statistics, machine learning and text analytics as folds over Spark rows."""

__version__ = "0.1.0"
