"""latentseg: per-label latent segmentation models for text at corpus scale, on Spark DataFrames."""
