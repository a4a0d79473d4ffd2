"""Functions of codes and slots, for numpy and for Columns."""
