"""Session-level helpers: scratch tables, code shipping, checked broadcasts."""
