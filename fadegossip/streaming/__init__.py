"""Streams: sources, sinks that keep a final table, windows, stateful grids and gossip epochs."""
