"""The driver-side search that decides which few candidates deserve a pass over the rows."""
