"""Choice of physical strategies by size."""
