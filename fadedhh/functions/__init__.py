"""Functions of the faded heavy-hitter engine."""
