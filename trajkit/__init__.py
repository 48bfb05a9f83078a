"""A DataFrame engine for the data side of agentic reinforcement learning."""
