"""Training-data operators: text, page and vector work that the matrix engine itself never imports."""
