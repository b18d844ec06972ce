"""Choice of physical strategy and of signature length from measured sizes."""
