"""Publishing personal tables with frequency-diverse cells, on Spark."""
