"""Path extrapolation over trajectory graphs, in Spark plans."""
