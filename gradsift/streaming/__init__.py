"""The online form of the loop, and windowed monitors."""
