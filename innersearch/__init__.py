"""innersearch: probabilistic maximum-inner-product search on PySpark DataFrames."""
