"""Methods over DataFrames: marking, sorting, packing, comparison, baselines and general operators."""
