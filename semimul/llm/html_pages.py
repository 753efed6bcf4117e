"""The small labelled table of web pages: text blocks begin with "+" where they are main text and with "-" where they are anything else.

The pages differ on purpose in what tells the two apart: some name their parts, most have nothing but the blocks themselves; some end or begin
with main text; some are one block; some have boilerplate in whole sentences.
"""

from __future__ import annotations

TRAINING_PAGES = (
    # parts that name themselves
    "<html><head><title>t</title></head><body><header><h1>-Daily site</h1></header><nav><ul><li><a href=/>-Home</a></li><li><a>-World news</a></li><li><a>-Sport</a></li></ul></nav><div class=ad>-Buy one now and get a second one for free today.</div><article><h1>+Storm reaches the coast</h1><p>+The storm reached the coast early on Monday and left thousands of homes without power, officials said.</p><p>+Short.</p><p>+Schools stay closed, and trains will not run before Tuesday evening. See <a>the timetable</a> for more on that.</p></article><footer>-&copy; Daily site. All rights reserved.</footer></body></html>",
    "<body><div id=menu><a>-Start</a> <a>-Shop</a> <a>-Contact</a></div><div class=content><h2>+How to plant a tree</h2><p>+Dig a hole that is twice as wide as the roots and just as deep. Water it well before the tree goes in.</p><ul><li>+A spade</li><li>+Two buckets of water, or more in a dry summer</li></ul><blockquote>+Plant in autumn, my grandmother used to say, and never in a hurry.</blockquote></div><div class=sidebar><h3>-Popular posts</h3><p>-<a>Ten ways to prune a rose</a></p><p>-<a>When to mow</a></p></div><div id=comments><h3>-Comments</h3><p>-I tried this last year and it worked very well, thank you for the clear guide to it all.</p><p>-Nice.</p></div><div id=footer><p>-About us. Imprint. We are a small team of gardeners that writes about trees and shrubs.</p></div></body>",
    "<body><div class='cookie-notice'>-We use cookies to give you the best experience on our site. By going on you agree to their use, as our policy says.</div><main><p>+It was late when they came to the inn. Nobody spoke.</p><p>+Well?</p><p>+The landlord looked up from his book, counted the guests twice and pointed up the narrow stairs behind the bar.</p><form>-Your name Your message Send us your opinion about this story.</form><p>+In the morning they were gone.</p></main><aside><p>-Read next: the inn at the end of the world, a story in three parts.</p></aside><footer><ul><li>-<a>Terms</a></li><li>-<a>Privacy</a></li></ul></footer></body>",
    "<body><article><h2>+Sources and further reading</h2><ul><li><a>+The history of the harbour</a></li><li><a>+A second book on the same matter, by its keeper</a></li></ul><p><a>+Map</a></p><p>+All of them can be read in the reading room on the first floor.</p><div class=promo>-Subscribe now and read all of our stories for a month, at no cost to you at all.</div><p>+Bring a pencil.</p></article><section class='reader-comments'><article class=comment><p>-The reading room is closed on Mondays, as I found out to my cost last week, so do ask before you go.</p></article></section></body>",
    "<body><nav><a>-Up</a></nav><article><p>+All there is to say is said in this one paragraph, which is not long.</p></article></body>",
    "<body><article><p>+A page of one paragraph and of nothing else, which says what it has to say and stops.</p></article></body>",
    "<article><p>+First of two paragraphs.</p><p>+The second one is the last block of the page and is followed by nothing.</p></article>",
    "<body><article><p>+Yes.</p></article></body>",
    "<body><article><h1>+A heading and no more</h1></article><footer>-Impressum</footer></body>",
    # nothing but the blocks
    "<body><table><tr><td><a>-Forum</a></td><td><a>-Members list</a></td><td><a>-Log in</a></td></tr></table><div>+The council met on Thursday to talk about the bridge. After three hours it had agreed on nothing but the date of its next meeting, in the first week of May.</div><div>+The mayor said that the old bridge could be used for one more winter, though not by lorries.</div><div>+Work may begin in June.</div><div><a>-Back to the list of all articles</a> | <a>-Print</a> | <a>-Next page</a></div><div>-Copyright 2020</div></body>",
    "<body><div><a>-Skip to the content</a></div><p>+Rivers carve valleys over thousands of years, and where the rock is hard they carve them narrow and deep, with walls that may rise a mile.</p><h2>+Soft rock</h2><p>+Where the rock is soft the valley widens.</p><p>+Floods move gravel and sand in a day that a calm river would not move in a year, and they leave fresh banks behind them.</p><div class=related><p>-Glaciers shape the land too, and you can read all about them in our long series on ice and snow.</p></div><div class='share social'>-Share this on your network of choice</div></body>",
    "<body><div><a>-One</a></div><div><a>-Two words</a></div><div><a>-Three words here</a></div><p>+One sentence of a text that has no element around it but the body, and that goes on for some words.</p><p>+Another one that follows it, with <a>a link</a> in the middle of its words, is part of the text as well.</p><div><a>-Imprint</a></div><div>-Contact</div></body>",
    "<p>+A text without any element around it but its own paragraph, twenty words long or somewhat longer, and the whole of its page.</p>",
    "<body><p>+The first words of this page are main text, since no menu stands before them and no name above them.</p><p>+Two words.</p><p>+The last words of it are main text too. After this full stop there is nothing, not even an imprint or a date.</p></body>",
    "<body><h1>+Notes on glass</h1><p>+Glass is sand that has been melted, cooled and kept from forming crystals, which takes soda, lime and a steady fire.</p><h2>+Colour</h2><p>+Iron makes it green. Cobalt makes it blue.</p><p>+Gold, in amounts too small to weigh on a kitchen scale, makes it red as no other metal can.</p><p>+See below.</p><h2>+Breaking</h2><p>+It breaks because of scratches that nobody sees, and strong glass is glass whose scratches are pressed shut.</p></body>",
    "<body><div><a>-Home</a> <a>-Reviews</a> <a>-Prices</a> <a>-About</a></div><div>-Welcome, guest</div><div><a>-Sign in</a> or <a>-join for free</a></div><h1>+A lamp for small rooms</h1><div>+The lamp stands on three legs, of which one is too short, and gives a light that is warm at the edge and cold in the middle.</div><div>+It costs little.</div><div>+I would buy it again, if only for the switch, which closes with a click that one can hear in the next room.</div><h3>-You may also like</h3><div><a>-A chair for large rooms and larger guests</a></div><div><a>-Five tables under a hundred</a></div><div><a>-What to do with old carpets</a></div><div>-All prices include tax</div></body>",
    "<body><div>-By going on to use this site you agree that we store small files on your machine. <a>-Read our policy on that</a> <a>-Accept all</a> <a>-Choose</a></div><div><a>-News</a></div><div><a>-Weather</a></div><div>-Monday</div><div><a>-Letters</a></div><p>+Snow fell on the pass in the night, and the road was shut at six, an hour before the first bus would have gone up it.</p><p>+Nobody was hurt. Two cars were left by the side of the road, and their drivers walked down to the village with a lamp.</p><p>+The road opens at noon.</p><div><a>-More from this region</a></div><div><a>-Winter tyres compared</a></div><div>-We are not responsible for the content of other sites. <a>-Terms</a> <a>-Privacy</a> <a>-Contact us</a></div></body>",
    "<body><ul><li><a>-Guides</a><li><a>-Tools</a><li><a>-Help</a></ul><h1>+Keeping bread fresh</h1><p>+Bread dries because the starch in it sets, and it sets fastest just above freezing, which is why the fridge is the worst place for it.</p><ul><li>+Cut side down</li><li>+In a cloth, never in foil</li><li>+Frozen in slices, if it has to last for more than three days</li></ul><p>+Old bread makes good soup.</p><h4>-Tags</h4><ul><li><a>-bread</a><li><a>-kitchen</a><li><a>-storing food</a></ul><p>-Page 1 of 3</p><p><a>-Older entries</a> <a>-Newer entries</a></p></body>",
    "<body><div><a>-Archive</a></div><div>-Vol. 7</div><div><a>-Issue four</a></div><div>-ISSN pending</div><div><a>-Editors</a></div><p>+We measured the height of the tide on forty days at the same pier and found it lower than the tables say on all but two of them.</p><p>+Table 1 gives the heights.</p><p>+The wind explains some of it. On days with wind from the land the water stood a hand lower, and on calm days it stood as the tables have it.</p><p>+We thank the keeper of the pier for his patience, and his dog.</p></body>",
    "<body><table><tr><td><a>-Top</a></td><td><a>-Search</a></td></tr><tr><td>-Date</td><td>-Author</td></tr></table><div>+She asked how long the ferry took, and he said that it depended on the cook, who liked to fish on the way over.</div><div>+\"And today?\"</div><div>+\"Today the cook is ill, and we shall be there by four o'clock, if the fog stays where it is.\"</div><div>+They were there by five.</div><div><a>-Previous chapter</a></div><div>-12</div><div><a>-Next chapter</a></div></body>",
    "<body><div><a>-Jobs</a> <a>-Offices</a> <a>-Press</a></div><h2>-Our offices</h2><div><a>-London</a></div><div><a>-Paris</a></div><h2>+What we do</h2><p>+We repair clocks in towers. There are fewer of them every year, and those that are left need us more often, so that the work stays much the same.</p><p>+A clock takes a week. A bell takes two, since it has to be taken down, and the street has to be closed for it.</p><h2>-Follow us</h2><div><a>-On the one network</a></div><div><a>-On the other</a></div><div>-Registered in Bern, number 4711</div></body>",
    "<body><p>+Salt was once paid for with gold, weight for weight, or so the story goes that every guide in the mine will tell.</p><p>+Nobody has found a bill for it.</p><p>+What has been found is a list of wages, in salt, for forty men and a boy, over one winter that must have been long.</p><div><a>-Back</a></div><div>-Printed on 4 May</div></body>",
    "<body><div><a>-EN</a> <a>-DE</a> <a>-FR</a></div><div>-Open daily from nine to five</div><div><a>-Tickets</a> <a>-How to find us</a></div><div>+The museum shows boats, and parts of boats, and the tools with which they were built over some four hundred years on this shore.</div><div>+The largest boat is outdoors, since no hall would hold it, and is painted once a year by the school.</div><div>-Join our circle of friends and get free entry for a year. <a>-Become a friend</a> <a>-Give a gift</a></div><div><a>-Imprint</a> <a>-Rules of the house</a></div></body>",
    "<body><p>+The answer is no.</p><p>+A rope that has held a fall may look as good as new, and it may even hold a second one, but nobody can tell you that it will.</p><p>+Cut it up.</p></body>",
    "<body><div><a>-Questions</a> <a>-Users</a></div><div>-3 votes</div><div><a>-edited last week</a></div><div>+To find the place in the list, halve it: look at the middle, and go on in the half that can hold what you look for.</div><div>+It has to be sorted.</div><div>+If it is not, sort it first, unless you will only look once, in which case just walk along it from one end.</div><div>-Not the answer you want? <a>-Ask your own question</a> or <a>-browse others like it</a></div><div>-7 people found this useful</div><div><a>-Privacy</a></div></body>",
    "<body><h1>+Two kinds of maps</h1><p>+There are maps that show where things are and maps that show how to get there, and they look nothing like each other.</p><p>+<a>The first kind</a> is drawn from above. <a>The second</a> is drawn from the road, and leaves out all that cannot be seen from it.</p><p>+Most people own both.</p></body>",
    # short blocks, and whole sentences that are not main text
    "<body><nav><a>-Poems</a></nav><main><h1>+Ferry</h1><p>+Grey boat</p><p>+Grey water</p><p>+Who goes</p><p>+Who stays</p><p>+One bell</p><h2>+II</h2><p>+Rope and rust and a cup of tea</p><p>+The far side</p></main><footer>-By the town library, which keeps the sheet with this poem.</footer></body>",
    "<body><div class='post entry'><h2>+Pancakes</h2><h3>+You need</h3><ul><li>+two eggs</li><li>+flour</li><li>+milk</li><li>+<a>butter</a></li></ul><h3>+Steps</h3><ol><li>+Mix</li><li>+Wait</li><li>+Fry on both sides in a hot pan</li></ol><p>+Serves four</p></div><div class=sidebar><p>-Our book of pancakes has ninety recipes. It can be had in any good shop.</p></div></body>",
    "<body><article><table><tr><th>+Year</th><th>+Ships</th></tr><tr><td>+1901</td><td>+12</td></tr><tr><td>+1902</td><td>+9</td></tr></table><h2>+Links</h2><p><a>+Register of ships</a></p><p><a>+All years</a></p><p>+photo by the author</p></article><div class=newsletter><p>-Do not miss a story. Leave us your address, and we will write to you each Friday.</p></div></body>",
    "<body><article><h1>+Lost and found</h1><p>+one glove</p><p>+umbrella</p><p>+a set of keys</p><p>+hat</p></article></body>",
    "<body><div class=story><h1>+Cast</h1><p>+A miller</p><p>+His son</p><p>+Two crows</p><div class='ad'>-New shoes. New you.</div><p>+Act one</p><p>+Enter the miller, with a sack that is too heavy for him and a hat that is too small</p><p>+Miller</p><p>+Good crows, be so kind and help me. I am old, and the hill is as high as it was when I was young.</p></div></body>",
    "<body><div>+The seeds are sown in March under glass and moved out when the nights are free of frost, which in the hills may be as late as June</div><div>+Rows a foot apart</div><div>+Water in the evening, never at noon, and keep the leaves dry as far as that can be done with a can</div><div>+Pick from August on</div></body>",
    "<body><div><a>-Sale</a></div><div>-Free shipping on all orders over fifty.</div><div><a>-Cart</a></div><div>-Questions? Call us.</div><div><a>-Stores</a> <a>-Sizes</a></div><p>+These boots were made to be mended, so the sole is sewn on and not glued, and the eyelets can be had as spare parts.</p><p>+Ours are four years old.</p><div><a>-Boots for children</a></div><div>-Sign up today and save ten in a hundred on your first order.</div><div><a>-Yes please</a></div><div>-All rights reserved. No part of this page may be copied.</div><div><a>-Terms of sale</a></div></body>",
    "<body><div><a>-Log in</a></div><div>-You are reading as a guest. Two texts are left this month.</div><div><a>-See offers</a></div><h1>+The last lighthouse</h1><p>+It has stood empty since the lamp began to light itself, and the stairs are closed to all but the man who cleans the glass.</p><p>+He comes on Tuesdays, by bicycle.</p><div><a>-Read also: the first lighthouse</a></div><div>-This text was first printed in May.</div><div><a>-Share</a> <a>-Print</a></div></body>",
    "<body><div><a>-A to Z</a> <a>-Index</a></div><p>+A knot holds because the rope is pressed on itself. The more it is pulled, the harder it is pressed, up to the point where it breaks.</p><div>-Did you like this page? <a>-Yes</a> <a>-No</a></div><div>-Last changed in spring.</div><div><a>-Report a fault</a></div></body>",
    # links that belong to an article, and a guest among them
    "<body><nav><a>-Back</a></nav><article><h1>+Reading list</h1><p>+These are the books that the course will use, in the order in which we shall need them.</p><h2>+First term</h2><p><a>+Tides and harbours, second edition</a></p><p>+out of print</p><p><a>+The pilot's year</a></p><p>+A short book, and a good one.</p><p><a>+Charts</a></p><h2>+Second term</h2><p><a>+A history of rope</a></p><p>+ask at the desk</p><p><a>+Knots</a></p></article><footer>-The library is open until ten.</footer></body>",
    "<body><div><a>-Courses</a></div><div class='main content'><p>+The museum has put its whole collection of ship models on show, and each of them now has a page of its own.</p><h3>+Where to find them</h3><p><a>+Models of sailing ships</a></p><p><a>+Models of steamers</a> and <a>+ferries</a></p><h3>+Elsewhere</h3><p><a>+Model harbours of the north</a></p><p>+in German</p><p><a>+A society for those who build them</a></p></div><div><a>-Top</a></div></body>",
)
