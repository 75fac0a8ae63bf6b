"""Where reads come from, and where results go."""
