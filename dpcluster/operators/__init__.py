"""Methods: clustering with and without privacy, and what they are built of."""
