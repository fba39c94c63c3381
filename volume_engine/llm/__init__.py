"""Training-data operators: text scoring, filtering, matching and layout over DataFrames."""

