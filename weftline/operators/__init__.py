"""Physical operators: encoders, models, measures and profiles over DataFrames."""
