"""Format knowledge: validators and what they tell about lengths and breaks."""
