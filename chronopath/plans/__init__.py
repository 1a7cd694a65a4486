"""Evolution, bounds, reduction and evaluation as DataFrame plans."""
