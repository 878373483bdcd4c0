"""anchorscope: from an anchor to recalled memory to scoped erasure samples, on Spark."""
