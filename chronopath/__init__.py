"""Path queries over many snapshots of a changing graph, as DataFrame plans."""
