"""Training-data operators: ten whole-corpus tools that share only the helpers of ``common``."""
