"""The chat model behind a small protocol: prompts in, validated configurations out."""
