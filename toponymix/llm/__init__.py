"""Training-data operators: ten corpus operators that share no code with the place-alias engine."""
