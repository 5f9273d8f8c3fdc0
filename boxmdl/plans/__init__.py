"""Choice of physical strategies by measured sizes."""
