"""The methods, their variants, the methods compared with, and the measures."""
