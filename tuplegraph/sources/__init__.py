"""Where relations come from and where graphs are kept."""
