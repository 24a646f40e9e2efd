"""layermul: sparse matrix products over semirings as Spark DataFrames, in one, two and three dimensions."""
