"""Column sketching on Spark: oblivious and learned sketches of wide matrices, and learning on them."""
