"""How rows find their rank: pivots, rounds, exchanges and delivery."""
