"""boolmat: sparse Boolean matrices in lossless compressed form, multiplied and ranked on Spark."""
