"""Streaming twins of the temporal codec and the flow counts."""
