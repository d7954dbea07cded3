"""The control plane: blocks are few, so layouts and query plans are computed on the driver from their sizes alone."""
