"""Few-pass graph connectivity and spanning forests on PySpark DataFrames."""
