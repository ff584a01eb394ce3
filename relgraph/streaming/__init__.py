"""Edge probabilities kept up to date by Structured Streaming."""
