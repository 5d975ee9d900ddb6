"""Cost estimates that choose between execution modes."""
