"""Small neural networks in numpy, trained over DataFrames."""
