"""deltamatch: continuous pattern matching and local spectra on Spark DataFrames."""

__version__ = "0.1.0"
