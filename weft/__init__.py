"""weft: learning interleaved sibling-order schemas from observed label sequences, on Spark."""
