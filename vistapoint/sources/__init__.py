"""Where fields of view come from and where they are kept."""
