"""cellstream: incomplete, outlier-laden seasonal tensor streams on Spark DataFrames."""
