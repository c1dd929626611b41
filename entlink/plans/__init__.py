"""Plans built from several operators: link strategies, relinking, stage timing."""
