"""The stages of training and classifying, and what they are compared with."""
