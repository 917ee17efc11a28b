"""The algebra, its rewrites, the builder, the text front end and the choice of executor."""
